"""Set intersection by window counts, and random graphs with power-law degrees."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, portable_hash
from ..functions.ranking import running
from ..sources.graph import TemporalBipartite
from ..sources.scratch import written


def reduce_sets(sets: DataFrame, shared: int = -1) -> TemporalBipartite:
    """sets: set_id (1, 2, ...), element. Left vertices are sets, right vertices elements and one extra that all sets share.

    Every edge of a set carries the set's number as its time, so a window [a, b] holds, for each two sets
    in it with k common elements, C(k + 1, 2) butterflies.
    """
    own = sets.select(F.col("set_id").alias("u"), F.col("element").alias("v"), F.col("set_id").alias("t"))
    extra = sets.select(F.col("set_id").alias("u"), F.lit(shared).alias("v"), F.col("set_id").alias("t")).distinct()
    return TemporalBipartite(own.unionByName(extra).select(*(F.col(c).cast("long") for c in "uvt")))


def intersection_windows(spark: SparkSession, a: int, b: int) -> DataFrame:
    """The four windows of the test whether sets a < b meet."""
    spans = [(a, b), (a + 1, b), (a, b - 1), (a + 1, b - 1)]
    return spark.createDataFrame([(i, x, y) for i, (x, y) in enumerate(spans)], "window_id long, t_start long, t_end long")


def intersection_size(counts: DataFrame) -> DataFrame:
    """c and common: the size of the intersection of the two sets at the windows' ends.

    Counts are prefix sums over pairs of sets, so the four windows leave C(k + 1, 2) of the one pair (a, b).
    A window whose start passes its end counts nothing.
    """
    signed = counts.agg(F.sum(F.when(F.col("window_id").isin(0, 3), F.col("butterflies")).otherwise(-F.col("butterflies"))).alias("c"))
    return signed.select("c", F.floor((F.sqrt(F.lit(1.0) + 8 * F.col("c")) - 1) / 2).cast("long").alias("common"))


def inverse_power(rank: Column, gamma: float, largest: int) -> Column:
    """Degree at a quantile in (0, 1] of a density proportional to d^-gamma on [1, largest]."""
    e = 1.0 - gamma
    return F.pow(1 + rank * (largest**e - 1), F.lit(1 / e))


def unit(c: Column, s: int, seed: int) -> Column:
    return (portable_hash([c, F.lit(s)], seed + s) + 0.5) / PRIME


def fine_unit(c: Column, s: int, seed: int) -> Column:
    """In (0, 1), from two hashes: as fine as many edges need."""
    return (portable_hash([c, F.lit(s)], seed + s) + unit(c, s + 101, seed)) / PRIME


def vertices(spark: SparkSession, of: int | DataFrame) -> tuple[DataFrame, int]:
    """id of each vertex, and how many there are: a number of them, or the keys of a table."""
    if isinstance(of, int):
        return spark.range(of), of
    ids = of.select(F.col(of.columns[0]).cast("long").alias("id")).distinct()
    return ids, ids.count()


def expected_degrees(spark: SparkSession, n_u: int | DataFrame, n_v: int | DataFrame, gamma_u: float, gamma_v: float, largest_u: int, largest_v: int, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """(u, du) and (v, dv): degrees at random quantiles. The right side is scaled to the left sum, and no degree of it passes largest_v."""
    (ids_u, _), (ids_v, n_v) = vertices(spark, n_u), vertices(spark, n_v)
    left = ids_u.select(F.col("id").alias("u"), inverse_power(unit(F.col("id"), 1, seed), gamma_u, largest_u).alias("du"))
    total = left.agg(F.sum("du")).first()[0]
    if total > n_v * largest_v:
        raise ValueError(f"{n_v} right vertices of degree {largest_v} at most can't hold {total:.0f} edges")
    drawn = inverse_power(unit(F.col("id"), 2, seed), gamma_v, largest_v) if gamma_v else F.lit(1.0)
    right = ids_v.select(F.col("id").alias("v"), drawn.cast("double").alias("dv"))
    scale, full = 0.0, -1
    while True:  # those at the bound only become more
        at_bound = F.col("dv") * scale >= largest_v
        n, rest = right.agg(F.count(F.when(at_bound, 1)), F.sum(F.when(~at_bound, F.col("dv")))).first()
        if n == full or not rest:
            break
        scale, full = (total - n * largest_v) / rest, n
    return left, right.select("v", F.least(F.lit(float(largest_v)), F.col("dv") * scale).alias("dv"))


def intervals(right: DataFrame) -> DataFrame:
    """v, low, high: the cumulated degrees around each vertex, by blocks of ids."""
    return running(right, "v", F.col("dv")).select("v", F.col("before").alias("low"), (F.col("before") + F.col("dv")).alias("high"))


def power_law(spark: SparkSession, n_u: int | DataFrame, n_v: int | DataFrame, gamma_u: float, gamma_v: float, largest_u: int, largest_v: int, seed: int = 1, exact: bool = False) -> TemporalBipartite:
    """Random graph whose expected degrees follow d^-gamma on both sides (gamma_v = 0: even degrees).

    exact draws every pair with probability d_u d_v / m (a cross join of two bounded ranges, for small
    graphs); otherwise each left vertex draws its expected number of edges and right ends by the cumulated
    degrees of the right side. Times are even on [1, number of edges].
    """
    left, right = expected_degrees(spark, n_u, n_v, gamma_u, gamma_v, largest_u, largest_v, seed)
    total = left.agg(F.sum("du")).first()[0]
    if exact:
        p = F.least(F.lit(1.0), F.col("du") * F.col("dv") / total)
        pairs = left.crossJoin(right).where(portable_hash([F.col("u"), F.col("v"), F.col("u") * 31 + F.col("v")], seed + 5) < p * PRIME).select("u", "v")
    else:
        count = F.floor(F.col("du") + unit(F.col("u"), 3, seed)).cast("int")
        stubs = left.select("u", F.explode(F.sequence(F.lit(1), F.greatest(count, F.lit(1)))).alias("k"))
        drawn = stubs.select("u", (fine_unit(F.col("u") * 131 + F.col("k"), 4, seed) * total).alias("x"))
        # A draw and the interval that holds it meet in a cell of width 1.
        cells = intervals(right).withColumn("cell", F.explode(F.sequence(F.floor("low"), F.floor("high"))))
        pairs = drawn.withColumn("cell", F.floor("x")).join(cells, "cell").where("low <= x and x < high").select("u", "v").distinct()
    m = pairs.count()
    t = 1 + F.pmod(portable_hash([F.col("u"), F.col("v")], seed + 9) * 7 + F.col("v"), F.lit(max(m, 1)))
    return TemporalBipartite(pairs.select("u", "v", t.cast("long").alias("t")))


def _uniforms(a: np.ndarray, b: np.ndarray, seed: int) -> np.ndarray:
    """In (0, 1): a mix of two whole numbers and a seed, so that a task that runs again draws the same."""
    h = a.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + b.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(seed * 0x165667B1 + 0x27D4EB2F)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        h = (h ^ (h >> np.uint64(shift))) * np.uint64(factor)
    return ((h ^ (h >> np.uint64(31))) >> np.uint64(11)).astype(np.float64) / (1 << 53) + 2.0**-54


def power_law_arrow(spark: SparkSession, n_u: int | DataFrame, n_v: int | DataFrame, gamma_u: float, gamma_v: float, largest_u: int, largest_v: int, seed: int = 1) -> TemporalBipartite:
    """The same law in one pass without joins: each left vertex draws its edges, right ends by the inverse of the cumulated degrees.

    A right vertex of quantile q has expected degree (1 + q K)^(1 / e), K = D^e - 1, e = 1 - gamma; the
    cumulated degree has a closed inverse. Quantiles are the ids themselves: low ids have high degrees.
    """
    ids, n_v = vertices(spark, n_u)[0], vertices(spark, n_v)[1]
    e_v = 1.0 - gamma_v
    k_v = largest_v**e_v - 1 if gamma_v else 0.0
    power = 1 / e_v + 1 if gamma_v else 1.0

    def right_end(x: np.ndarray) -> np.ndarray:
        if not gamma_v:
            return np.minimum((x * n_v).astype(np.int64), n_v - 1)
        if abs(power) < 1e-12:
            q = (np.exp(x * np.log1p(k_v)) - 1) / k_v
        else:
            q = ((1 + x * ((1 + k_v) ** power - 1)) ** (1 / power) - 1) / k_v
        return np.minimum(((1 - q) * n_v).astype(np.int64), n_v - 1)

    def run(batches):
        for batch in batches:
            u = batch.column(0).to_numpy()
            e = 1.0 - gamma_u
            degree = (1 + _uniforms(u, u * 0 + 1, seed) * (largest_u**e - 1)) ** (1 / e) if gamma_u else np.ones(len(u))
            n = np.maximum(1, np.floor(degree + _uniforms(u, u * 0 + 2, seed))).astype(np.int64)
            for at in range(0, len(u), 1024):  # a vertex has at most largest_u edges
                own, k = np.repeat(u[at : at + 1024], n[at : at + 1024]), n[at : at + 1024]
                number = np.arange(len(own)) - np.repeat(np.cumsum(k) - k, k) + 3
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array(right_end(_uniforms(own, number, seed)), pa.int64())], ["u", "v"])

    pairs = written(ids.mapInArrow(run, "u long, v long").distinct(), "power-law")
    m = pairs.count()
    t = 1 + F.pmod(portable_hash([F.col("u"), F.col("v")], seed + 9) * 7 + F.col("v"), F.lit(max(m, 1)))
    return TemporalBipartite(pairs.select("u", "v", t.cast("long").alias("t")))


def uniformity(g: TemporalBipartite, bins: int = 20) -> DataFrame:
    """One row: edges, chi_square of their times over equal bins of [1, edges], degrees of freedom."""
    total = g.edges.agg(F.count("*").alias("edges"))
    binned = g.edges.crossJoin(F.broadcast(total)).select("edges", F.floor((F.col("t") - 1) * bins / F.col("edges")).alias("bin"))
    per = binned.groupBy("bin").agg(F.count("*").alias("n"), F.first("edges").alias("edges"))
    share = F.col("edges") / bins
    return per.agg(F.first("edges").alias("edges"), F.round(F.sum(F.pow(F.col("n") - share, F.lit(2)) / share), 6).alias("chi_square"), F.lit(bins - 1).alias("freedom"))


def balance(g: TemporalBipartite, left: DataFrame | None = None, right: DataFrame | None = None) -> DataFrame:
    """Sums of degrees on both sides and the largest degrees; with the expected degrees also their sums, which must agree."""
    pairs = g.edges.select("u", "v").distinct()
    u = pairs.groupBy("u").count().agg(F.sum("count").alias("sum_u"), F.max("count").alias("max_u"))
    v = pairs.groupBy("v").count().agg(F.sum("count").alias("sum_v"), F.max("count").alias("max_v"))
    both = u.crossJoin(v)
    if left is None or right is None:
        return both
    return both.crossJoin(left.agg(F.sum("du").alias("expected_u"))).crossJoin(right.agg(F.sum("dv").alias("expected_v")))
