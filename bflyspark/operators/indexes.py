"""Enumerated, grouped and hybrid indexes; choice of the cutoff; sampled versions."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, kept, portable_hash
from ..functions.intervals import choose2, compose_stairs, signed_points
from ..functions.ranking import running
from ..sources.graph import TemporalBipartite
from ..sources.scratch import written
from . import dominance, lists, tiles
from .wedges import GROUP, group_points, group_sizes, priority_wedges, with_stairs

POINT_BYTES = 24  # l, r, w
GROUPED_POINT_BYTES = 41  # side, x, z, l, r, w
MATES = 2000  # points of a group that one task pairs with the others; a larger group is split


@dataclass(frozen=True)
class Index:
    """points: l, r, w of the enumerated part; groups: side, x, z, l, r, w of the grouped part.

    lists holds the same groups packed, those of more than meta["size"] wedges; a scan counts from it without an exchange.
    """

    points: DataFrame | None
    groups: DataFrame | None
    meta: dict = field(default_factory=dict)
    lists: DataFrame | None = None


def grouped_points(packed: DataFrame, above: int = 1) -> DataFrame:
    """side, x, z, l, r, w of the groups of more than `above` wedges; single wedges make no butterfly."""
    return lists.points(packed, max(2, above + 1)).drop("size")


def wedge_sizes(g: TemporalBipartite) -> DataFrame:
    """size, groups of all groups, written once."""
    return written(tiles.histogram(g), "group-sizes")


def enumerate_points(groups: DataFrame) -> DataFrame:
    """One signed point per butterfly, equal ones added up, from each group's signed points.

    With c the sum of w over alive points, C(c, 2) is the sum over pairs i < j of w_i w_j at
    (least l, greatest r) plus (w_i^2 - w_i) / 2 at each point itself; so repeated intervals are
    paired by their weights and never expanded. A large group is paired by several tasks, each of which
    holds a share of it against the whole.
    """
    sized = groups if "size" in groups.columns else groups.withColumn("size", F.count("*").over(Window.partitionBy(*GROUP)))
    last = F.floor((F.col("size") - 1) / MATES)
    a = sized.select(*GROUP, F.pmod(F.xxhash64("l", "r"), last + 1).alias("share"), F.struct("l", "r").alias("p"), F.col("w").alias("wp"))
    b = sized.select(*GROUP, F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("share"), F.struct("l", "r").alias("q"), F.col("w").alias("wq"))
    pairs = a.join(b, [*GROUP, "share"]).where("p < q").select(F.least("p.l", "q.l").alias("l"), F.greatest("p.r", "q.r").alias("r"), (F.col("wp") * F.col("wq")).alias("w"))
    own = groups.select("l", "r", choose2(F.col("w")).alias("w")).where("w <> 0")
    return pairs.unionByName(own).groupBy("l", "r").agg(F.sum("w").alias("w")).where("w <> 0")


def build_enumerated(g: TemporalBipartite) -> Index:
    return Index(written(lists.enumerated(lists.build(g)), "enumerated"), None)


def query_enumerated(index: Index, windows: DataFrame, layout: str = "scan") -> DataFrame:
    return dominance.count(index.points, windows, layout).withColumnRenamed("cnt", "butterflies")


def build_grouped(g: TemporalBipartite) -> Index:
    packed = lists.build(g)
    return Index(None, grouped_points(packed), {"size": 1}, packed)


def grouped_partial(groups: DataFrame, windows: DataFrame, layout: str = "scan") -> DataFrame:
    """window_id, cnt: sum of C(c, 2) over groups.

    scan reads every point for every window. packed walks one array per group. dyadic looks up one running
    sum per tree node of a group (logarithmic, all in the engine). sweep answers a whole batch of windows
    from each group's own sorted structure, group after group.
    """
    keys = tuple(GROUP)
    if layout == "sweep":
        return dominance.sweep_groups(groups, windows, keys)
    if layout == "packed":
        keyed = dominance.query_packed(dominance.packed_groups(groups, keys), windows, keys)
    elif layout == "dyadic":
        keyed = dominance.dyadic(groups, windows, keys)
    else:
        keyed = dominance.scan(groups, windows, keys)
    return keyed.groupBy("window_id").agg(F.sum(choose2(F.col("cnt"))).alias("cnt"))


def query_grouped(index: Index, windows: DataFrame, layout: str = "scan") -> DataFrame:
    return dominance.all_windows(windows, large_counts(index, windows, layout)).withColumnRenamed("cnt", "butterflies")


def large_counts(index: Index, windows: DataFrame, layout: str = "scan", groups: DataFrame | None = None) -> DataFrame:
    """window_id, cnt of the grouped part; groups: the same rows, dealt otherwise."""
    if index.lists is not None and layout == "scan" and groups is None:
        return lists.counted(index.lists, windows, max(2, index.meta["size"] + 1)).select("window_id", "cnt")
    return grouped_partial(index.groups if groups is None else groups, windows, layout)


@dataclass(frozen=True)
class Cutoff:
    """Groups of more than `size` wedges are grouped. Of those with exactly size + 1 wedges, `tie_quota` go to the enumerated side."""

    size: int
    tie_quota: int
    alpha: float
    est_bytes: int


def size_histogram(sizes: DataFrame) -> DataFrame:
    """size, groups, butterflies: at most one row per degree. From a row per group, from groups by size, or from points with their group's size."""
    groups = F.sum("groups") if "groups" in sizes.columns else F.expr("sum(w) div first(size)") if "w" in sizes.columns else F.count("*")
    return sizes.groupBy("size").agg(groups.alias("groups")).withColumn("butterflies", choose2(F.col("size")) * F.col("groups"))


def cutoff_by_share(sizes: DataFrame, alpha: float, rule: str = "atmost", ties: str = "class") -> Cutoff:
    """Walk the sizes upwards while the enumerated share of butterflies stays at most (or below) alpha."""
    rows = size_histogram(sizes).orderBy("size").collect()  # bounded by the largest degree
    total = sum(r.butterflies for r in rows)
    limit = alpha * total
    fits = (lambda n: n <= limit) if rule == "atmost" else (lambda n: n < limit)
    done, size, quota = 0, 0, 0
    for r in rows:
        if fits(done + r.butterflies) or not r.butterflies:
            done, size = done + r.butterflies, r.size
            continue
        if ties == "exact":
            each = r.size * (r.size - 1) // 2
            quota = max(0, min(r.groups, int((limit - done) // each)))
            while quota and not fits(done + quota * each):
                quota -= 1
            done += quota * each
        break
    return Cutoff(size, quota, done / total if total else 1.0, _bytes(rows, size, quota))


def _bytes(rows, size: int, quota: int) -> int:
    enumerated = sum(r.butterflies for r in rows if r.size <= size)
    grouped = sum(r.size * r.groups for r in rows if r.size > size)
    if quota:
        step = size + 1
        enumerated, grouped = enumerated + quota * (step * (step - 1) // 2), grouped - quota * step
    return enumerated * POINT_BYTES + grouped * GROUPED_POINT_BYTES


def cutoff_by_memory(sizes: DataFrame, limit_bytes: int, distinct_times: int | None = None) -> Cutoff:
    """Raise alpha from 0 by the smallest groups, and stop before the estimated size passes the limit.

    distinct_times bounds the enumerated side by its number of different points.
    """
    rows = size_histogram(sizes).where("size >= 2").orderBy("size").collect()  # bounded by the largest degree
    total = sum(r.butterflies for r in rows)
    most = distinct_times * (distinct_times + 1) // 2 if distinct_times else None
    grouped = sum(r.size * r.groups for r in rows) * GROUPED_POINT_BYTES
    done = size = 0
    estimate = grouped
    for r in rows:
        rest = grouped - r.size * r.groups * GROUPED_POINT_BYTES
        points = done + r.butterflies if most is None else min(done + r.butterflies, most)
        if points * POINT_BYTES + rest > limit_bytes and points * POINT_BYTES + rest > estimate:
            break
        done, size, grouped, estimate = done + r.butterflies, r.size, rest, points * POINT_BYTES + rest
    return Cutoff(size, 0, done / total if total else 1.0, estimate)


def split_groups(rows: DataFrame, cutoff: Cutoff) -> tuple[DataFrame, DataFrame]:
    """Rows of the small (enumerated) and of the large (grouped) side; single wedges are on neither. rows: GROUP, size, any others."""
    small = rows.where((F.col("size") >= 2) & (F.col("size") <= cutoff.size))
    large = rows.where((F.col("size") >= 2) & (F.col("size") > cutoff.size))
    if not cutoff.tie_quota:
        return small, large
    step = large.agg(F.min("size")).first()[0]
    keys = large.where(F.col("size") == step).select(*GROUP).distinct()
    per_end = running(keys.groupBy((-F.col("x")).alias("end")).agg(F.count("*").alias("n")), "end", F.col("n"))
    ranked = keys.withColumn("end", -F.col("x")).join(per_end, "end").withColumn("rank", F.col("before") + F.row_number().over(Window.partitionBy("end").orderBy(F.desc("z"), "side")))
    moved = written(ranked.where(F.col("rank") <= cutoff.tie_quota).select(*GROUP), "moved-groups")
    return small.unionByName(large.join(moved, GROUP, "left_semi")), large.join(moved, GROUP, "left_anti")


def build_hybrid(g: TemporalBipartite, alpha: float | None = None, limit_bytes: int | None = None, rule: str = "atmost", ties: str = "class") -> Index:
    """The split by a share of butterflies, or by a limit of bytes. Edges are packed once; only numbers of groups by size come to the driver."""
    packed = lists.build(g)
    sizes = written(lists.histogram(packed), "group-sizes")
    cutoff = cutoff_by_memory(sizes, limit_bytes) if alpha is None else cutoff_by_share(sizes, alpha, rule, ties)
    meta = {"alpha": cutoff.alpha, "size": cutoff.size, "est_bytes": cutoff.est_bytes}
    if cutoff.tie_quota:
        small, large = split_groups(written(lists.points(packed), "group-points"), cutoff)
        return Index(enumerate_points(small), large.drop("size"), meta)
    return Index(written(lists.enumerated(packed, cutoff.size), "enumerated"), grouped_points(packed, cutoff.size), meta, packed)


def prune(index: Index, windows: DataFrame) -> Index:
    """The points of a stored index that some window can count; ranges of l that lie before all windows aren't read."""
    if "step" not in index.meta or index.points is None:
        return index
    low, high = windows.agg(F.min("t_start"), F.max("t_end")).first()
    if low is None:
        return index
    cell = (low - index.meta["low"]) // index.meta["step"]
    return Index(index.points.where((F.col("part_l") >= cell) & (F.col("l") >= low) & (F.col("r") <= high)), index.groups, index.meta)


def query_hybrid(index: Index, windows: DataFrame, layout: str = "scan", grouped_layout: str = "scan", parallelism: int | None = None) -> DataFrame:
    """Sum of both parts; independent parts are read by as many tasks as there are partitions."""
    index = prune(index, windows)
    groups = None if parallelism is None else index.groups.repartition(parallelism, *GROUP)
    first = dominance.count(index.points, windows, layout).select("window_id", "cnt")
    both = first.unionByName(large_counts(index, windows, grouped_layout, groups)).groupBy("window_id").agg(F.sum("cnt").alias("cnt"))
    return dominance.all_windows(windows, both).withColumnRenamed("cnt", "butterflies")


# Sampled versions


def butterflies(stairs: DataFrame) -> DataFrame:
    """side, x, z, y, w, stairs: one row per butterfly, middles in order. Never stored at scale."""
    a = stairs.select(*GROUP, "y", F.col("stairs").alias("s1"))
    b = stairs.select(*GROUP, F.col("y").alias("w"), F.col("stairs").alias("s2"))
    return a.join(b, GROUP).where("y < w").select(*GROUP, "y", "w", compose_stairs(F.col("s1"), F.col("s2")).alias("stairs"))


def drawn_pairs(sizes: DataFrame, share: float, seed: int) -> DataFrame:
    """side, x, z, i, j (i < j, from 0): pairs of a group's wedges, each drawn with probability share, by numbers alone.

    Pairs of a group are numbered; every stretch of 1 / share numbers draws one place in it by a hash. So
    the work is that of the sample, not that of all pairs.
    """
    pairs = choose2(F.col("size"))
    stretch = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((pairs - 1) * share).cast("long"))).alias("stretch")
    at = (portable_hash([F.col("x"), F.col("z"), F.col("stretch"), F.col("side").cast("long")], seed) + 0.5) / PRIME
    number = F.floor((F.col("stretch") + at) / share).cast("long")
    drawn = sizes.where("size >= 2").select(*GROUP, "size", stretch).withColumn("number", number).where(F.col("number") < pairs)
    j = F.floor((1 + F.sqrt(1 + 8 * F.col("number").cast("double"))) / 2).cast("long")
    exact = F.when(choose2(j) > F.col("number"), j - 1).when(choose2(j + 1) <= F.col("number"), j + 1).otherwise(j)  # roots of large numbers are rounded
    return drawn.withColumn("j", exact).select(*GROUP, (F.col("number") - choose2(F.col("j"))).alias("i"), "j")


def thin_butterflies(stairs: DataFrame, share: float, seed: int) -> DataFrame:
    """Butterflies of drawn pairs of wedges; a share of 1 takes all. Only drawn pairs are joined."""
    if share >= 1:
        return butterflies(stairs)
    ranked = stairs.select(*GROUP, "y", "stairs", (F.row_number().over(Window.partitionBy(*GROUP).orderBy("y")).cast("long") - 1).alias("rank"))
    drawn = drawn_pairs(group_sizes(stairs), share, seed)
    a = ranked.select(*GROUP, "y", F.col("rank").alias("i"), F.col("stairs").alias("s1"))
    b = ranked.select(*GROUP, F.col("y").alias("w"), F.col("rank").alias("j"), F.col("stairs").alias("s2"))
    both = drawn.join(a, [*GROUP, "i"]).join(b, [*GROUP, "j"])
    return both.select(*GROUP, "y", "w", compose_stairs(F.col("s1"), F.col("s2")).alias("stairs"))


def thin_wedges(stairs: DataFrame, share: float, seed: int) -> DataFrame:
    return stairs.where(kept([F.col("x"), F.col("z"), F.col("y")], share, seed))


def build_sampled(g: TemporalBipartite, alpha: float, share1: float, share2: float = 1.0, seed: int = 1, rule: str = "atmost") -> Index:
    """share1 of the enumerated butterflies and share2 of the grouped wedges. Only butterflies that are drawn by number need wedges as rows."""
    packed = lists.build(g)
    cutoff = cutoff_by_share(written(lists.histogram(packed), "group-sizes"), alpha, rule)
    if cutoff.size < 2:
        points = g.edges.sparkSession.createDataFrame([], "l long, r long, w long")
    elif share1 >= 1:
        points = lists.enumerated(packed, cutoff.size)
    else:
        stairs = with_stairs(priority_wedges(g))
        sized = written(stairs.withColumn("size", F.count("*").over(Window.partitionBy(*GROUP))), "sized-wedges")
        few = thin_butterflies(split_groups(sized, cutoff)[0], share1, seed)
        points = few.select(F.explode(signed_points(F.col("stairs"))).alias("p")).groupBy(F.col("p.l").alias("l"), F.col("p.r").alias("r")).agg(F.sum("p.w").alias("w"))
    groups = lists.points(packed, max(2, cutoff.size + 1), share2, seed + 1).drop("size")
    return Index(points, groups, {"share1": share1, "share2": share2, "alpha": cutoff.alpha, "size": cutoff.size, "seed": seed}, packed)


def query_sampled(index: Index, windows: DataFrame) -> DataFrame:
    """kept_points, kept_pairs, estimate and its standard error per window."""
    q1, q2 = index.meta["share1"], index.meta["share2"]
    first = dominance.scan(index.points, windows).select("window_id", F.col("cnt").alias("kept_points"))
    drawn = lists.counted(index.lists, windows, max(2, index.meta["size"] + 1), q2, index.meta["seed"] + 1)
    second = drawn.select("window_id", F.col("cnt").alias("kept_pairs"), "spread")
    both = windows.join(first, "window_id", "left").join(second, "window_id", "left").na.fill(0, ["kept_points", "kept_pairs"]).na.fill(0.0, ["spread"])
    estimate = F.col("kept_points") / q1 + F.col("kept_pairs") / (q2 * q2)
    error = F.sqrt(F.col("kept_points") / q1 * (1 - q1) / q1 + F.col("spread"))
    return both.select("window_id", "t_start", "t_end", F.col("kept_points").cast("long"), F.col("kept_pairs").cast("long"), F.round(estimate, 6).alias("estimate"), F.round(error, 6).alias("std_error"))
