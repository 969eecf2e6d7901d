"""Uses of window counts: trends, busiest windows, ego networks, communities, co-purchase, similarity."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.graph import TemporalBipartite, project
from ..sources.windows import sliding
from .baselines import recount
from .indexes import Index, query_hybrid
from .wedges import GROUP, priority_wedges


def trend(spark: SparkSession, index: Index, low: int, high: int, length: int, step: int) -> DataFrame:
    """Counts of windows of one length that slide by a step."""
    return query_hybrid(index, sliding(spark, low, high, length, step))


def ego(g: TemporalBipartite, vertex: int, side: str = "u") -> TemporalBipartite:
    """Edges among a vertex, its neighbours and their neighbours: two semi joins."""
    other = "v" if side == "u" else "u"
    near = g.edges.where(F.col(side) == vertex).select(other).distinct()
    return TemporalBipartite(g.edges.join(near, other, "left_semi").select("u", "v", "t"))


def busiest(counts: DataFrame) -> DataFrame:
    """The window with most butterflies; the earliest on ties."""
    return counts.agg(F.max_by("t_start", F.struct("butterflies", -F.col("t_start"))).alias("t_start"), F.max("butterflies").alias("butterflies"))


def busiest_window(spark: SparkSession, g: TemporalBipartite, vertex: int, low: int, high: int, length: int, step: int, side: str = "u") -> DataFrame:
    return busiest(recount(ego(g, vertex, side), sliding(spark, low, high, length, step)))


def community_trend(g: TemporalBipartite, labels: DataFrame, windows: DataFrame, vertex: int | None = None) -> DataFrame:
    """label, window_id, butterflies: each community's own subgraph. labels: v, label (few, broadcast by size).

    All communities and windows go through one plan: a community is a part of the window's id.
    """
    edges = g.edges if vertex is None else ego(g, vertex).edges
    labelled = edges.join(labels, "v")
    inside = F.col("t").between(F.col("t_start"), F.col("t_end"))
    pairs = labelled.join(F.broadcast(windows), inside).select("label", "window_id", "u", "v").distinct()
    wedges = priority_wedges(pairs=pairs, by=("label", "window_id"), with_times=False)
    c = wedges.groupBy("label", "window_id", *GROUP).agg(F.count("*").alias("c"))
    counts = c.groupBy("label", "window_id").agg(F.sum(F.shiftright(F.col("c") * (F.col("c") - 1), 1)).alias("butterflies"))
    every = labels.select("label").distinct().crossJoin(F.broadcast(windows.select("window_id")))
    return every.join(counts, ["label", "window_id"], "left").select("label", "window_id", F.coalesce("butterflies", F.lit(0)).cast("long").alias("butterflies"))


def co_purchase(g: TemporalBipartite, windows: DataFrame, k: int) -> DataFrame:
    """window_id, v1, v2, buyers, rank: the k pairs of right vertices with most common left ones."""
    pairs = project(g, windows)
    a = pairs.select("window_id", "u", F.col("v").alias("v1"))
    b = pairs.select("window_id", "u", F.col("v").alias("v2"))
    counts = a.join(b, ["window_id", "u"]).where("v1 < v2").groupBy("window_id", "v1", "v2").agg(F.count("*").alias("buyers"))
    rank = F.row_number().over(Window.partitionBy("window_id").orderBy(F.desc("buyers"), "v1", "v2"))
    return counts.withColumn("rank", rank).where(F.col("rank") <= k)


def kernel_vector(counts: DataFrame) -> DataFrame:
    """One row: counts by window as an array. Windows are few."""
    return counts.agg(F.transform(F.array_sort(F.collect_list(F.struct("window_id", "butterflies"))), lambda x: x["butterflies"]).alias("vector"))


def kernel_similarity(a: DataFrame, b: DataFrame) -> DataFrame:
    """Cosine of two vectors of counts."""
    both = a.select(F.col("vector").alias("x")).crossJoin(b.select(F.col("vector").alias("y")))
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda i, j: i.cast("double") * j), F.lit(0.0), lambda s, v: s + v)
    return both.select(F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 6).alias("cosine"))
