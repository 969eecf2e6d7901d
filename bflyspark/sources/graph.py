"""Bipartite graphs with timestamped edges: contract, projection, degrees, priority, census."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ranking import running

SIDE_U, SIDE_V = 0, 1
BROADCAST_ROWS = 2_000_000  # rows of three whole numbers


@dataclass(frozen=True)
class TemporalBipartite:
    """edges: u, v, t as bigint. The side of a vertex is its column, so equal ids on both sides stay apart."""

    edges: DataFrame

    @property
    def pairs(self) -> DataFrame:
        """u, v and the sorted distinct times of each pair."""
        return self.edges.groupBy("u", "v").agg(F.array_sort(F.collect_set("t")).alias("times"))

    def swapped(self) -> TemporalBipartite:
        return TemporalBipartite(self.edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "t"))


def _given(name: str) -> Column:
    c = F.col(name).cast("long")
    return F.when(c.isNull(), F.raise_error(F.lit(f"{name} of an edge is null"))).otherwise(c)


def from_table(df: DataFrame, u: str = "u", v: str = "v", t: str = "t") -> TemporalBipartite:
    """An edge table checked for nulls: reading a null vertex or time fails the query."""
    return TemporalBipartite(df.select(_given(u).alias("u"), _given(v).alias("v"), _given(t).alias("t")))


def in_windows(edges: DataFrame, windows: DataFrame, cells: int = 256) -> DataFrame:
    """Rows of edges with the id of each closed window that holds their time, by an equi-join on cells of time.

    A window stands in every cell that it touches. That table is broadcast as long as it has BROADCAST_ROWS
    rows at most; a larger batch of windows is joined by a shuffle.
    """
    n, low, high = windows.agg(F.count("*"), F.min("t_start"), F.max("t_end")).first()
    width = max(1, ((high or 0) - (low or 0)) // cells + 1)
    cell = lambda c: F.floor((c - F.lit(low or 0)) / width)
    touched = windows.where("t_start <= t_end").select("window_id", "t_start", "t_end", F.explode(F.sequence(cell(F.col("t_start")), cell(F.col("t_end")))).alias("cell"))
    if n * cells <= BROADCAST_ROWS:
        touched = F.broadcast(touched)
    placed = edges.where(F.col("t").between(F.lit(low), F.lit(high))).withColumn("cell", cell(F.col("t")))
    return placed.join(touched, "cell").where(F.col("t").between(F.col("t_start"), F.col("t_end"))).select("window_id", *edges.columns)


def project(g: TemporalBipartite, windows: DataFrame) -> DataFrame:
    """window_id, u, v: pairs with a time inside the closed window, once each."""
    return in_windows(g.edges, windows).select("window_id", "u", "v").distinct()


def restrict(g: TemporalBipartite, low: int, high: int) -> TemporalBipartite:
    """Edges of one window; the filter reaches the scan."""
    return TemporalBipartite(g.edges.where(F.col("t").between(low, high)))


def compact_time(g: TemporalBipartite) -> tuple[TemporalBipartite, DataFrame]:
    """Times as dense ranks from 1, and the table rank -> time. Ranks are numbers by blocks of times; the engine picks the join."""
    ranks = running(g.edges.select("t").distinct(), "t").select("t", (F.col("before") + 1).alias("rank"))
    edges = g.edges.join(ranks, "t").select("u", "v", F.col("rank").alias("t"))
    return TemporalBipartite(edges), ranks


def grain(g: TemporalBipartite, width: int) -> TemporalBipartite:
    """Times in whole steps of width; exact for windows on the grain."""
    return TemporalBipartite(g.edges.withColumn("t", F.expr(f"t div {int(width)}")))


def unique_degrees(pairs: DataFrame, *by: str) -> DataFrame:
    """side, id, deg: neighbours counted once per pair (per window with by='window_id')."""
    u = pairs.groupBy(*by, "u").agg(F.count("*").alias("deg")).select(*by, F.lit(SIDE_U).alias("side"), F.col("u").alias("id"), "deg")
    v = pairs.groupBy(*by, "v").agg(F.count("*").alias("deg")).select(*by, F.lit(SIDE_V).alias("side"), F.col("v").alias("id"), "deg")
    return u.unionByName(v)


def priority_key(deg: Column, side: Column, id_: Column) -> Column:
    """Smaller is more important: larger degree first, then the right side, then the smaller id. Compared, never sorted."""
    return F.struct((-deg).alias("d"), (-side.cast("int")).alias("s"), id_.alias("i"))


def census(g: TemporalBipartite, dmin: int = 1) -> DataFrame:
    """One row: vertices, edges, pairs, times, mean smaller degree, degree exponent per side."""
    pairs = g.edges.select("u", "v").distinct()
    du = pairs.groupBy("u").agg(F.count("*").alias("du"))
    dv = pairs.groupBy("v").agg(F.count("*").alias("dv"))
    joined = pairs.join(du, "u").join(dv, "v")
    fit = lambda d: F.round(1 + F.count("*") / F.sum(F.log(F.col(d) / (dmin - 0.5))), 6)
    per_edge = joined.agg(F.count("*").alias("pairs"), F.round(F.avg(F.least("du", "dv")), 6).alias("mean_min_degree"))
    edges = g.edges.agg(F.count("*").alias("edges"), F.countDistinct("t").alias("times"))
    left = du.where(F.col("du") >= dmin).agg(F.count("*").alias("n_u"), F.max("du").alias("max_u"), fit("du").alias("exponent_u"))
    right = dv.where(F.col("dv") >= dmin).agg(F.count("*").alias("n_v"), F.max("dv").alias("max_v"), fit("dv").alias("exponent_v"))
    return per_edge.crossJoin(edges).crossJoin(left).crossJoin(right)
