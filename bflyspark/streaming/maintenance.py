"""Append-only maintenance of an index: new edges add the points that they make, and nothing is rebuilt.

State: pairs (u, v, times), group points (side, x, z, l, r, w) of the wedges with ends on one side, and
points (l, r, w) of the butterflies. Ends are ordered by id, so that growing degrees move no group.

A batch changes some pairs. Each wedge with a changed pair is found by joining the changed pairs with the
neighbours of their middles; the difference of its signed points after and before is D. With P the old
points of a group, C(p + d, 2) - C(p, 2) = p d + (d^2 - d) / 2, so the new points are P crossed with D and
the points of D alone. Edges may come late: their times play no part in what is read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.intervals import signed_points, wedge_stairs
from ..operators.dominance import count
from ..operators.indexes import enumerate_points
from ..operators.wedges import GROUP
from ..sources.graph import SIDE_V
from ..sources.scratch import written


@dataclass(frozen=True)
class State:
    pairs: DataFrame
    groups: DataFrame
    points: DataFrame


def empty(spark: SparkSession) -> State:
    return State(
        spark.createDataFrame([], "u long, v long, times array<long>"),
        spark.createDataFrame([], "side int, x long, z long, l long, r long, w long"),
        spark.createDataFrame([], "l long, r long, w long"),
    )


def compacted(points: DataFrame, *keys: str) -> DataFrame:
    return points.groupBy(*keys, "l", "r").agg(F.sum("w").alias("w")).where("w <> 0")


def changed_points(pairs: DataFrame) -> DataFrame:
    """D: side, x, z, l, r, w. pairs: u, v, old (null before), times, with changed."""
    arcs = pairs.select(F.col("u").alias("y"), F.col("v").alias("end"), "old", "times", "changed")
    one = arcs.where("changed").select("y", *(F.col(c).alias(f"{c}1") for c in ("end", "old", "times")))
    two = arcs.select("y", *(F.col(c).alias(f"{c}2") for c in ("end", "old", "times")), F.col("changed").alias("changed2"))
    both = one.join(two, "y").where("end1 <> end2 and (not changed2 or end1 < end2)")
    after = signed_points(wedge_stairs(F.col("times1"), F.col("times2")))
    before = F.when(F.col("old1").isNotNull() & F.col("old2").isNotNull(), signed_points(wedge_stairs(F.col("old1"), F.col("old2"))))
    gone = F.transform(F.coalesce(before, F.array().cast("array<struct<l:bigint,r:bigint,w:bigint>>")), lambda p: F.struct(p["l"].alias("l"), p["r"].alias("r"), (-p["w"]).alias("w")))
    rows = both.select(F.lit(SIDE_V).alias("side"), F.least("end1", "end2").alias("x"), F.greatest("end1", "end2").alias("z"), F.inline(F.concat(after, gone)))
    return compacted(rows, *GROUP)


def delta(groups: DataFrame, changed: DataFrame) -> DataFrame:
    """New butterflies' points (l, r, w) from the old points of the groups that change, and from the change itself."""
    old = groups.select(*GROUP, F.col("l").alias("l1"), F.col("r").alias("r1"), F.col("w").alias("w1"))
    new = changed.select(*GROUP, F.col("l").alias("l2"), F.col("r").alias("r2"), F.col("w").alias("w2"))
    crossed = old.join(new, GROUP).select(F.least("l1", "l2").alias("l"), F.greatest("r1", "r2").alias("r"), (F.col("w1") * F.col("w2")).alias("w"))
    return compacted(crossed.unionByName(enumerate_points(changed)))


def append(state: State, edges: DataFrame, label: str = "state") -> tuple[State, DataFrame]:
    """The state with a batch of edges (u, v, t) taken in, and the points that the batch adds. Tables are written anew, computed once."""
    fresh = edges.groupBy("u", "v").agg(F.collect_set("t").alias("new"))
    both = state.pairs.withColumnRenamed("times", "old").join(fresh, ["u", "v"], "full_outer")
    times = F.array_sort(F.array_union(F.coalesce("old", F.array().cast("array<bigint>")), F.coalesce("new", F.array().cast("array<bigint>"))))
    merged = both.select("u", "v", "old", times.alias("times"), (F.col("new").isNotNull() & (F.col("old").isNull() | (F.size(F.array_except("new", F.coalesce("old", F.array().cast("array<bigint>")))) > 0))).alias("changed"))
    pairs = written(merged, f"{label}-pairs")
    changed = written(changed_points(pairs), f"{label}-changed")
    added = written(delta(state.groups, changed), f"{label}-added")
    groups = written(compacted(state.groups.unionByName(changed), *GROUP), f"{label}-groups")
    points = written(compacted(state.points.unionByName(added)), f"{label}-points")
    return State(pairs.select("u", "v", "times"), groups, points), added


def counts(state: State, windows: DataFrame, layout: str = "scan") -> DataFrame:
    return count(state.points, windows, layout).withColumnRenamed("cnt", "butterflies")
