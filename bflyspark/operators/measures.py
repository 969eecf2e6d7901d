"""Clustering coefficient, three-paths, degrees and partners per window; cost and error measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.intervals import choose2
from ..sources.graph import TemporalBipartite, census, project, unique_degrees
from .dominance import all_windows
from .indexes import GROUPED_POINT_BYTES, POINT_BYTES, Index, query_hybrid, size_histogram
from .wedges import group_sizes, priority_wedges


def three_paths(g: TemporalBipartite, windows: DataFrame, projected: DataFrame | None = None) -> DataFrame:
    """Paths of three edges: the sum over pairs of (deg_u - 1)(deg_v - 1)."""
    pairs = project(g, windows) if projected is None else projected
    du = pairs.groupBy("window_id", "u").agg(F.count("*").alias("du"))
    dv = pairs.groupBy("window_id", "v").agg(F.count("*").alias("dv"))
    both = pairs.join(du, ["window_id", "u"]).join(dv, ["window_id", "v"])
    return all_windows(windows, both.groupBy("window_id").agg(F.sum((F.col("du") - 1) * (F.col("dv") - 1)).alias("three_paths")), "three_paths")


def clustering(counts: DataFrame, paths: DataFrame) -> DataFrame:
    """window_id, butterflies, three_paths and 4 B / P3 (null without a path)."""
    both = counts.join(paths.select("window_id", "three_paths"), "window_id", "full_outer")
    ratio = F.when(F.col("three_paths") > 0, F.round(4 * F.col("butterflies") / F.col("three_paths"), 9))
    return both.select("window_id", "butterflies", "three_paths", ratio.alias("bcc"))


def bcc(index: Index, g: TemporalBipartite, windows: DataFrame) -> DataFrame:
    return clustering(query_hybrid(index, windows), three_paths(g, windows))


def mean_degree(g: TemporalBipartite, windows: DataFrame, side: str = "u") -> DataFrame:
    """Pairs per active vertex of a side (publications per author)."""
    pairs = project(g, windows)
    return pairs.groupBy("window_id").agg(F.round(F.count("*") / F.countDistinct(side), 6).alias("mean_degree"))


def mean_partners(g: TemporalBipartite, windows: DataFrame, side: str = "u") -> DataFrame:
    """Distinct partners on the same side per active vertex (collaborators per author)."""
    other = "v" if side == "u" else "u"
    pairs = project(g, windows).select("window_id", F.col(side).alias("a"), F.col(other).alias("y"))
    mates = pairs.join(pairs.select("window_id", F.col("a").alias("b"), "y"), ["window_id", "y"]).where("a <> b").select("window_id", "a", "b").distinct()
    partners = mates.groupBy("window_id").agg(F.count("*").alias("links"))
    active = pairs.groupBy("window_id").agg(F.countDistinct("a").alias("active"))
    return active.join(partners, "window_id", "left").select("window_id", F.round(F.coalesce("links", F.lit(0)) / F.col("active"), 6).alias("mean_partners"))


def relative_error(estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """window_id, error: null where the exact count is 0."""
    both = estimates.select("window_id", "estimate").join(exact.select("window_id", "butterflies"), "window_id")
    return both.select("window_id", F.when(F.col("butterflies") > 0, F.round(F.abs(F.col("estimate") - F.col("butterflies")) / F.col("butterflies"), 9)).alias("error"))


def error_bounds(counts: DataFrame, vertices: int, share1: float, share2: float) -> DataFrame:
    """window_id, bound_one, bound_two: the two published bounds without their constants.

    counts: window_id, enumerated, grouped (exact counts of both parts, B and S). sqrt(B ln n / share1) and
    (S ln n)^0.75 * share2^-1.75, with n the number of vertices.
    """
    log_n = F.log(F.lit(float(max(vertices, 2))))
    one = F.sqrt(F.col("enumerated") * log_n / share1)
    two = F.pow(F.col("grouped") * log_n, F.lit(0.75)) * share2**-1.75
    return counts.select("window_id", F.round(one, 6).alias("bound_one"), F.round(two, 6).alias("bound_two"))


def work_counters(g: TemporalBipartite) -> DataFrame:
    """One row: join candidates, wedges, groups, groups of two or more, butterflies, largest group."""
    pairs = g.edges.select("u", "v").distinct()
    deg = unique_degrees(pairs)
    du = deg.where("side = 0").select(F.col("id").alias("u"), F.col("deg").alias("du"))
    dv = deg.where("side = 1").select(F.col("id").alias("v"), F.col("deg").alias("dv"))
    candidates = pairs.join(du, "u").join(dv, "v").agg(F.sum(F.least("du", "dv")).alias("candidates"))
    sizes = group_sizes(priority_wedges(pairs=pairs, with_times=False))
    hist = size_histogram(sizes)
    total = hist.agg(F.sum(F.col("size") * F.col("groups")).alias("wedges"), F.sum("groups").alias("groups"), F.sum(F.when(F.col("size") >= 2, F.col("groups")).otherwise(0)).alias("groups_many"), F.sum("butterflies").alias("butterflies"), F.max("size").alias("largest"))
    return candidates.crossJoin(total)


def summary(g: TemporalBipartite) -> DataFrame:
    """Census and work counters in one row."""
    return census(g).crossJoin(work_counters(g))


def index_size(index: Index) -> DataFrame:
    """Points and estimated bytes of each part."""
    parts = []
    for name, table, width in (("enumerated", index.points, POINT_BYTES), ("grouped", index.groups, GROUPED_POINT_BYTES)):
        if table is not None:
            parts.append(table.agg(F.lit(name).alias("part"), F.count("*").alias("points"), (F.count("*") * width).alias("bytes")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the files below a path, as the file system of the path tells them."""
    jvm, conf = spark._jvm, spark._jsparkSession.sessionState().newHadoopConf()
    at = jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(conf).getContentSummary(at).getLength()


def concentration_share(sizes: DataFrame, below: int = 10, grouped_above: int | None = None) -> DataFrame:
    """One row: groups, share of groups under a size; share of the heavy ones (over half of the largest size, or over a given one) among groups and butterflies."""
    hist = size_histogram(sizes)
    top = hist.agg(F.max("size").alias("largest"))
    both = hist.crossJoin(top)
    heavy = F.col("size") > (F.col("largest") / 2 if grouped_above is None else F.lit(grouped_above))
    return both.agg(
        F.sum("groups").alias("groups"),
        F.round(F.sum(F.when(F.col("size") < below, F.col("groups")).otherwise(0)) / F.sum("groups"), 6).alias("share_small"),
        F.round(F.sum(F.when(heavy, F.col("groups")).otherwise(0)) / F.sum("groups"), 6).alias("share_heavy"),
        F.round(F.sum(F.when(heavy, F.col("butterflies")).otherwise(0)) / F.greatest(F.sum("butterflies"), F.lit(1)), 6).alias("butterflies_heavy"),
    )


def work_done(index: Index, points: DataFrame) -> DataFrame:
    """One row: pairs expanded by the enumerated part, points after compaction, their ratio. points: sized group points."""
    size = index.meta["size"]
    pairs = points.where(F.col("size").between(2, size)).groupBy("side", "x", "z").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum(choose2(F.col("n"))), F.lit(0)).alias("pairs"))
    after = index.points.agg(F.count("*").alias("points"))
    return pairs.crossJoin(after).select("pairs", "points", F.round(F.col("points") / F.greatest("pairs", F.lit(1)), 6).alias("compaction"))
