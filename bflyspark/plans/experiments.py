"""Experiments over settings: memory limits, sampling shares, threads, generated graphs, durations, all graphs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, duration, hardness, indexes, measures
from ..sources import catalog, store, windows
from ..sources.graph import TemporalBipartite, census
from ..sources.scratch import scratch

# Settings of the experiments.
SHARES = [(1.0, 1.0), (0.08, 1.0), (0.018, 1.0), (0.01, 0.5), (0.001, 0.05)]
EXPONENTS = [(2.1, 2.1), (2.5, 2.5), (2.9, 2.9), (2.1, 0.0), (2.5, 0.0), (2.9, 0.0)]
THREADS = [1, 2, 4, 8]


def spent(frame: DataFrame) -> float:
    """Seconds to compute all rows and columns."""
    began = time.time()
    frame.write.format("noop").mode("overwrite").save()
    return round(time.time() - began, 3)


def stored_index(index: indexes.Index, spark: SparkSession) -> tuple[indexes.Index, int, float]:
    """The index written and read back, its bytes at rest, and the seconds of the write."""
    path = scratch(spark, "experiment")
    began = time.time()
    store.save(index, path)
    took = round(time.time() - began, 3)
    return store.load(spark, path), measures.stored_bytes(spark, path), took


def memory_limits(spark: SparkSession, g: TemporalBipartite, w: DataFrame, tenths: list[int]) -> list[dict]:
    """Limits as tenths of the pure enumerated size: alpha, bytes estimated and stored, seconds to build and to ask."""
    sizes = indexes.wedge_sizes(g)
    full = sum(r.butterflies for r in indexes.size_histogram(sizes).collect()) * indexes.POINT_BYTES
    out = []
    for tenth in tenths:
        index, size, built = stored_index(indexes.build_hybrid(g, limit_bytes=full * tenth // 10), spark)
        out.append({"tenth": tenth, "alpha": round(index.meta["alpha"], 6), "est_bytes": index.meta["est_bytes"], "stored_bytes": size, "build_s": built, "query_s": spent(indexes.query_hybrid(index, w, "sweep", "sweep"))})
    return out


def shares(spark: SparkSession, g: TemporalBipartite, w: DataFrame, alpha: float = 0.5) -> list[dict]:
    """The five settings of both shares: points, mean and largest error, seconds to build and to ask."""
    exact = baselines.recount(g, w).persist()
    out = []
    for one, two in SHARES:
        built = indexes.build_sampled(g, alpha, one, two, seed=3)
        index, size, took = stored_index(built, spark)
        answer = indexes.query_sampled(indexes.Index(index.points.drop("part_l"), index.groups, built.meta), w)
        seconds = spent(answer)
        error = measures.relative_error(answer, exact).agg(F.avg("error").alias("mean"), F.max("error").alias("worst")).first()
        out.append({"share1": one, "share2": two, "stored_bytes": size, "mean_error": error["mean"], "max_error": error["worst"], "build_s": took, "query_s": seconds})
    exact.unpersist()
    return out


def threads(spark: SparkSession, g: TemporalBipartite, w: DataFrame, few: DataFrame) -> list[dict]:
    """Seconds of the hybrid batch and of the recount when stages have so many tasks."""
    key = "spark.sql.shuffle.partitions"
    before = spark.conf.get(key)
    index, _, _ = stored_index(indexes.build_hybrid(g, alpha=0.5), spark)
    out = []
    try:
        for n in THREADS:
            spark.conf.set(key, n)
            held = indexes.Index(index.points.coalesce(n), index.groups.coalesce(n), index.meta)
            out.append({"threads": n, "hybrid_s": spent(indexes.query_hybrid(held, w, "sweep", "sweep", n)), "recount_s": spent(baselines.recount(TemporalBipartite(g.edges.coalesce(n)), few, n))})
    finally:
        spark.conf.set(key, before)
    return out


def thread_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """threads, hybrid, recount: totals over the fixed windows; the number of tasks changes nothing."""
    g, w = catalog.load(spark, sf_dir, "g6"), windows.fixed(spark, windows.FIXED_HOURS)
    index = indexes.build_hybrid(g, alpha=0.5)
    out = None
    for n in (THREADS[0], THREADS[-1]):
        a = indexes.query_hybrid(index, w, parallelism=n).agg(F.sum("butterflies").alias("hybrid"))
        b = baselines.recount(g, w, parallelism=n).agg(F.sum("butterflies").alias("recount"))
        row = a.crossJoin(b).select(F.lit(n).cast("long").alias("threads"), "hybrid", "recount")
        out = row if out is None else out.unionByName(row)
    return out


def generated_counts(spark: SparkSession, sf_dir: str, n: int = 600) -> DataFrame:
    """gamma_u, gamma_v, edges, by hybrid and by recount: butterflies of generated graphs in three windows of their time line."""
    out = None
    for gamma_u, gamma_v in EXPONENTS:
        g = hardness.power_law_arrow(spark, n, n, gamma_u, gamma_v, 60, 60, seed=11)
        m = g.edges.count()
        w = windows.fixed(spark, [(1, m), (m // 4, m), (1, m // 2)])
        a = indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.5), w).agg(F.sum("butterflies").alias("hybrid"))
        b = baselines.recount(g, w).agg(F.sum("butterflies").alias("recount"))
        row = a.crossJoin(b).select(F.lit(gamma_u).alias("gamma_u"), F.lit(gamma_v).alias("gamma_v"), F.lit(m).cast("long").alias("edges"), "hybrid", "recount")
        out = row if out is None else out.unionByName(row)
    return out


def summaries(spark: SparkSession, sf_dir: str, names: list[str]) -> DataFrame:
    """graph, pairs, edges, n_u, n_v of each graph: the summary of the data sets in one table."""
    out = None
    for name in names:
        row = census(catalog.load(spark, sf_dir, name)).select(F.lit(name).alias("graph"), "pairs", "edges", "n_u", "n_v", "mean_min_degree")
        out = row if out is None else out.unionByName(row)
    return out


def bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """window_id, bound_one, bound_two on the customer-supplier graph, for shares of a half each at alpha 0.5."""
    g, w = catalog.load(spark, sf_dir, "g1"), windows.fixed(spark, windows.FIXED_DAYS)
    index = indexes.build_hybrid(g, alpha=0.5)
    row = census(g).first()
    one = indexes.query_enumerated(indexes.Index(index.points, None), w).select("window_id", F.col("butterflies").alias("enumerated"))
    two = indexes.query_grouped(indexes.Index(None, index.groups, index.meta, index.lists), w).select("window_id", F.col("butterflies").alias("grouped"))
    return measures.error_bounds(one.join(two, "window_id"), row.n_u + row.n_v, 0.5, 0.5)


def durations(spark: SparkSession, g: TemporalBipartite, deltas: list[int]) -> dict:
    """Seconds: build once, ask all thresholds, and the direct counter for one threshold."""
    frame = spark.createDataFrame([(d,) for d in deltas], "delta long")
    began = time.time()
    index = duration.build(g, max(deltas))
    built = round(time.time() - began, 3)
    return {"build_s": built, "query_s": spent(duration.query(index, frame)), "direct_one_s": spent(baselines.duration_count(g, sorted(deltas)[len(deltas) // 2])), "thresholds": len(deltas)}
