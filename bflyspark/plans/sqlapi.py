"""SQL names: views of a graph and window functions over them."""

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.dominance import merge_tree_counts
from ..operators.indexes import Index
from ..sources.graph import TemporalBipartite

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def register_tables(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def register_graph(g: TemporalBipartite, windows: DataFrame, prefix: str = "g") -> None:
    g.edges.createOrReplaceTempView(f"{prefix}_edges")
    windows.createOrReplaceTempView(f"{prefix}_windows")


#: Counts per window as one statement over the views: project, wedges by id order, sums of C(c, 2).
RECOUNT = """
WITH p AS (SELECT DISTINCT w.window_id, e.u, e.v FROM {prefix}_edges e JOIN {prefix}_windows w ON e.t BETWEEN w.t_start AND w.t_end),
c AS (SELECT a.window_id, a.v AS v1, b.v AS v2, count(*) AS c FROM p a JOIN p b ON a.window_id = b.window_id AND a.u = b.u AND a.v < b.v GROUP BY 1, 2, 3)
SELECT w.window_id, w.t_start, w.t_end, coalesce(sum(c * (c - 1) / 2), 0) AS butterflies
FROM {prefix}_windows w LEFT JOIN c ON w.window_id = c.window_id GROUP BY 1, 2, 3
"""


def recount_sql(spark: SparkSession, prefix: str = "g") -> DataFrame:
    out = spark.sql(RECOUNT.format(prefix=prefix))
    return out.withColumn("butterflies", F.col("butterflies").cast("long"))


def lateral_count(spark: SparkSession, index: Index, windows: DataFrame) -> DataFrame:
    """Dominance counts by a lateral join."""
    index.points.createOrReplaceTempView("bfly_points")
    windows.createOrReplaceTempView("bfly_windows")
    return spark.sql("SELECT q.window_id, q.t_start, q.t_end, c.butterflies FROM bfly_windows q, LATERAL (SELECT coalesce(sum(p.w), 0) AS butterflies FROM bfly_points p WHERE p.l >= q.t_start AND p.r <= q.t_end) c")


def union_of_stairs(intervals: DataFrame, keys: list[str]) -> DataFrame:
    """keys, l, r: of each key's intervals those that hold no other one: one walk from the largest l on, keeping the least r."""

    def walk(rows: pd.DataFrame) -> pd.DataFrame:
        order = np.lexsort((rows["r"].to_numpy(), -rows["l"].to_numpy()))
        r = rows["r"].to_numpy()[order]
        least = np.minimum.accumulate(r)
        fresh = np.concatenate([[True], r[1:] < least[:-1]])
        return rows.iloc[order[fresh]]

    schema = intervals.select(*keys, "l", "r")
    return schema.groupBy(*keys).applyInPandas(walk, schema.schema)


#: Body of a window function: C(c, 2) over pairs of right vertices, or paths of three edges, between two times.
COUNTED = """
(SELECT coalesce(sum(c * (c - 1) DIV 2), 0L) FROM (SELECT count(*) AS c FROM (SELECT DISTINCT u, v FROM {prefix}_edges WHERE t BETWEEN low AND high) a
 JOIN (SELECT DISTINCT u, v AS v2 FROM {prefix}_edges WHERE t BETWEEN low AND high) b ON a.u = b.u AND a.v < b.v2 GROUP BY a.v, b.v2))"""
PATHS = """
(SELECT coalesce(sum((du - 1) * (dv - 1)), 0L) FROM (SELECT count(*) OVER (PARTITION BY u) AS du, count(*) OVER (PARTITION BY v) AS dv FROM (SELECT DISTINCT u, v FROM {prefix}_edges WHERE t BETWEEN low AND high)))"""


def register_functions(spark: SparkSession, prefix: str | None = None) -> None:
    """SQL functions: choose2(c); bfly_nodes(start, height), a table function of tree nodes; with a registered graph's prefix also bfly_count(low, high) and bfly_three_paths(low, high)."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="level int, node bigint")
    class Nodes:
        def eval(self, start: int, height: int):
            low, high, level = start, 1 << height, 0
            while low < high:
                if low & 1:
                    yield level, low
                    low += 1
                if high == 1:
                    if low == 0:
                        yield level, 0
                    break
                low, high, level = low >> 1, high >> 1, level + 1

    spark.udtf.register("bfly_nodes", Nodes)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION choose2(c BIGINT) RETURNS BIGINT RETURN c * (c - 1) DIV 2")
    if prefix:
        for name, body in (("bfly_count", COUNTED), ("bfly_three_paths", PATHS)):
            spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(low BIGINT, high BIGINT) RETURNS BIGINT RETURN {body.format(prefix=prefix)}")


def packed_udf(windows: DataFrame):
    """A vectorised function: arrays of l, r, w of a group -> array of counts, one per window in order of id."""
    rows = sorted((r.window_id, r.t_start, r.t_end) for r in windows.collect())  # a batch of windows
    start, end = np.array([r[1] for r in rows]), np.array([r[2] for r in rows])

    @F.pandas_udf("array<bigint>")
    def count(ls: pd.Series, rs: pd.Series, ws: pd.Series) -> pd.Series:
        return pd.Series([merge_tree_counts(np.asarray(a), np.asarray(b), np.asarray(c), start, end).tolist() for a, b, c in zip(ls, rs, ws, strict=True)])

    return count
