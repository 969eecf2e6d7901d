"""Counting points (l, r, w) with l >= t_start and r <= t_end, for batches of windows.

scan    every point against every window, map-side summed; for few points or few windows
grid    prefix sums over all pairs of coordinates, one look-up per window; for few distinct times
dyadic  each point in one node per level of a binary tree over l, running sums by r inside; a window
        asks one node per level; for many points, many windows and many times
sweep   a merge tree per partition of points, answered for all windows in numpy; for offline batches
packed  sorted arrays per key, counted inside an expression; for many middle-sized keys

With keys (the grouped index) dyadic keeps a tree per key, and sweep_groups answers a batch of windows from
sums over each key's ranks, or from a merge tree for a key of many points.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LAYOUTS = ("scan", "grid", "dyadic", "sweep")


def all_windows(windows: DataFrame, counts: DataFrame, value: str = "cnt") -> DataFrame:
    """Every window, with 0 where nothing was counted."""
    return windows.join(counts, "window_id", "left").select(*windows.columns, F.coalesce(F.col(value), F.lit(0)).cast("long").alias(value))


def scan(points: DataFrame, windows: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    inside = (F.col("l") >= F.col("t_start")) & (F.col("r") <= F.col("t_end"))
    return points.join(F.broadcast(windows), inside).groupBy("window_id", *keys).agg(F.sum("w").alias("cnt"))


def build_grid(points: DataFrame) -> DataFrame:
    """l, r, total for every pair of coordinates: points with l' >= l and r' <= r. Squares of distinct times."""
    compact = points.groupBy("l", "r").agg(F.sum("w").alias("w"))
    ls, rs = compact.select("l").distinct(), compact.select("r").distinct()
    dense = ls.crossJoin(rs).where("l <= r").join(compact, ["l", "r"], "left").withColumn("w", F.coalesce("w", F.lit(0)))
    by_l = dense.withColumn("s", F.sum("w").over(Window.partitionBy("r").orderBy(F.desc("l")).rowsBetween(Window.unboundedPreceding, 0)))
    # A cell below the diagonal has no row, so the second pass runs over r for the same l and sees all r' <= r.
    return by_l.select("l", "r", F.sum("s").over(Window.partitionBy("l").orderBy("r").rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


def query_grid(grid: DataFrame, windows: DataFrame) -> DataFrame:
    """One cell per window: the smallest l from t_start on, the largest r up to t_end."""
    ls, rs = grid.select("l").distinct(), grid.select("r").distinct()
    low = windows.join(ls, F.col("l") >= F.col("t_start")).groupBy("window_id").agg(F.min("l").alias("l"))
    high = windows.join(rs, F.col("r") <= F.col("t_end")).groupBy("window_id").agg(F.max("r").alias("r"))
    return low.join(high, "window_id").join(grid, ["l", "r"]).select("window_id", F.col("total").alias("cnt"))


def grid(points: DataFrame, windows: DataFrame) -> DataFrame:
    return query_grid(build_grid(points), windows)


def tree_height(points: DataFrame) -> tuple[int, int]:
    """Least l and the height of a binary tree over l."""
    low, high = points.agg(F.min("l"), F.max("l")).first()
    return (0, 0) if low is None else (low, int(high - low).bit_length())


def build_dyadic(points: DataFrame, low: int, height: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys, level, node, r, cum: running sums by r in each tree node. Rows: points times height."""
    level = F.explode(F.sequence(F.lit(0), F.lit(height))).alias("level")
    copies = points.select(*keys, (F.col("l") - low).alias("at"), "r", "w", level)
    nodes = copies.withColumn("node", F.expr("shiftright(at, level)")).groupBy(*keys, "level", "node", "r").agg(F.sum("w").alias("w"))
    return nodes.select(*keys, "level", "node", "r", F.sum("w").over(Window.partitionBy(*keys, "level", "node").orderBy("r").rowsBetween(Window.unboundedPreceding, 0)).alias("cum"))


def window_nodes(windows: DataFrame, low: int, height: int) -> DataFrame:
    """The at most height + 1 nodes that cover l >= t_start, for each window."""
    start = F.least(F.greatest(F.col("t_start") - low, F.lit(0)), F.lit(1 << height)).cast("long")
    up = windows.withColumn("p", start).withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(height))))
    at = up.withColumn("node", F.expr("shiftright(p + shiftleft(1L, level) - 1, level)"))
    odd = (F.col("node") % 2 == 1) & (F.col("node") < F.expr(f"shiftleft(1L, {height} - level)"))
    root = (F.col("level") == height) & (F.col("p") == 0)
    return at.where(odd | root).select("window_id", "t_end", "level", "node")


def query_dyadic(tree: DataFrame, windows: DataFrame, low: int, height: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """As-of look-up of each node's last running sum at r <= t_end: a union sorted by r, no range join.

    With keys, a window asks those nodes of its cover that a key has, if they hold a point in time at all.
    """
    asked = window_nodes(windows, low, height)
    if keys:
        least = tree.groupBy(*keys, "level", "node").agg(F.min("r").alias("least"))
        asked = least.join(asked, ["level", "node"]).where("least <= t_end").drop("least")
    both = tree.select(*keys, "level", "node", "r", "cum", F.lit(0).alias("ask"), F.lit(None).cast("long").alias("window_id")).unionByName(asked.select(*keys, "level", "node", F.col("t_end").alias("r"), F.lit(None).cast("long").alias("cum"), F.lit(1).alias("ask"), "window_id"))
    order = Window.partitionBy(*keys, "level", "node").orderBy("r", "ask").rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("seen", F.last("cum", ignorenulls=True).over(order)).where("ask = 1")
    return found.groupBy("window_id", *keys).agg(F.sum(F.coalesce("seen", F.lit(0))).alias("cnt"))


def dyadic(points: DataFrame, windows: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    low, height = tree_height(points)
    return query_dyadic(build_dyadic(points, low, height, keys), windows, low, height, keys)


def merge_tree_counts(l: np.ndarray, r: np.ndarray, w: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:  # noqa: E741
    """Weights of points with l >= start and r <= end, for all windows at once.

    Points in falling l; a window's points are a prefix, cut into blocks of powers of two; inside each
    block points stand by r with running sums.
    """
    order = np.argsort(-l, kind="stable")
    l, r, w = l[order], r[order], w[order]  # noqa: E741
    n = np.searchsorted(-l, -start, "right")
    out = np.zeros(len(start), np.int64)
    level, done = 0, np.zeros(len(start), np.int64)
    kinds, rank = np.unique(r, return_inverse=True)
    upto = np.searchsorted(kinds, end, "right")  # ranks below this are in
    for level in reversed(range(max(1, int(len(l)).bit_length()))):
        width = 1 << level
        block = np.arange(len(l)) >> level
        key = block * (len(kinds) + 1) + rank
        place = np.argsort(key, kind="stable")
        total = np.concatenate([[0], np.cumsum(w[place])])
        use = (n >> level & 1).astype(bool)
        first = done[use]
        lo = np.searchsorted(key[place], (first >> level) * (len(kinds) + 1), "left")
        hi = np.searchsorted(key[place], (first >> level) * (len(kinds) + 1) + upto[use], "left")
        out[use] += total[hi] - total[lo]
        done[use] += width
    return out


def sweep(points: DataFrame, windows: DataFrame, batch: int = 1 << 18) -> DataFrame:
    """Partial counts per partition of points for all windows. Windows are a batch of bounded size on the driver."""
    ids, starts, ends = (windows.toArrow().column(k).to_numpy() for k in ("window_id", "t_start", "t_end"))

    def run(batches):
        total, held, n = np.zeros(len(ids), np.int64), [], 0

        def flush():
            cols = [np.concatenate([h[k] for h in held]) for k in range(3)]
            return merge_tree_counts(*cols, starts, ends)

        for b in batches:
            held.append([b.column(k).to_numpy(zero_copy_only=False) for k in range(3)])
            n += b.num_rows
            if n >= batch:
                total += flush()
                held, n = [], 0
        if n:
            total += flush()
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(total, pa.int64())], ["window_id", "part"])

    return points.select("l", "r", "w").mapInArrow(run, "window_id long, part long").groupBy("window_id").agg(F.sum("part").alias("cnt"))


GRID_POINTS = 512


class Batch:
    """Windows in order of their starts and of their ends, so that ranks of a group's points are found by counting."""

    def __init__(self, start: np.ndarray, end: np.ndarray):
        self.start, self.end = start, end
        self.starts, self.ends = np.sort(start), np.sort(end)
        self.by_start, self.by_end = np.argsort(np.argsort(start, kind="stable")), np.argsort(np.argsort(end, kind="stable"))

    def counts(self, l: np.ndarray, r: np.ndarray, w: np.ndarray) -> np.ndarray:  # noqa: E741
        """Weight of one group's points inside each window: sums over all pairs of ranks, two look-ups a window; a merge tree for more points."""
        n = len(l)
        if n > GRID_POINTS:
            return merge_tree_counts(l, r, w, self.start, self.end)
        first = np.searchsorted(self.starts, np.sort(l), "right")  # windows from here on start behind the point
        last = np.searchsorted(self.ends, np.sort(r), "left")  # windows from here on end at or behind it
        i = np.cumsum(np.bincount(first, minlength=len(self.start) + 1))[self.by_start]
        j = np.cumsum(np.bincount(last, minlength=len(self.end) + 1))[self.by_end]
        table = np.zeros((n + 1, n + 1), np.int64)
        np.add.at(table, (np.argsort(np.argsort(l, kind="stable"), kind="stable"), np.argsort(np.argsort(r, kind="stable"), kind="stable") + 1), w)
        table = np.cumsum(np.cumsum(table[::-1], axis=0)[::-1], axis=1)
        return table[i, j]


def sweep_groups(groups: DataFrame, windows: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """window_id, cnt: the sum over keys of C(c, 2), c the key's weight inside the window. A batch of windows goes to every task."""
    ids, starts, ends = (windows.toArrow().column(k).to_numpy() for k in ("window_id", "t_start", "t_end"))

    def run(batches):
        batch, total = Batch(starts, ends), np.zeros(len(ids), np.int64)
        held: list[np.ndarray] = []

        def solve(l, r, w):  # noqa: E741
            c = batch.counts(l, r, w)
            np.add(total, c * (c - 1) // 2, out=total)

        def whole(cols: list[np.ndarray], final: bool) -> list[np.ndarray]:
            """Solve the groups that are complete; the last one may go on in the next batch."""
            names = cols[:-3]
            fresh = np.zeros(len(cols[0]), bool)
            for c in names:
                fresh[1:] |= c[1:] != c[:-1]
            edges = [0, *np.flatnonzero(fresh).tolist()]
            for a, b in zip(edges, edges[1:] + [len(fresh)], strict=True):
                if b < len(fresh) or final:
                    solve(*(c[a:b] for c in cols[-3:]))
            return [] if final else [c[edges[-1] :] for c in cols]

        for b in batches:
            if b.num_rows:
                new = [b.column(k).to_numpy(zero_copy_only=False) for k in range(b.num_columns)]
                held = whole([np.concatenate(x) for x in zip(held, new, strict=True)] if held else new, False)
        if held:
            whole(held, True)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(total, pa.int64())], ["window_id", "part"])

    dealt = groups.select(*keys, "l", "r", "w").repartition(*keys).sortWithinPartitions(*keys)
    return dealt.mapInArrow(run, "window_id long, part long").groupBy("window_id").agg(F.sum("part").alias("cnt"))


def packed_groups(points: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """One row per key with its points in an array, by r."""
    return points.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("r", "l", "w"))).alias("pts"), F.min("l").alias("first"), F.max("r").alias("last"))


def query_packed(groups: DataFrame, windows: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """window_id, keys, cnt: the sum over each key's array; keys outside the window are passed over."""
    near = groups.join(F.broadcast(windows), (F.col("last") >= F.col("t_start")) & (F.col("first") <= F.col("t_end")))
    inside = lambda p: (p["l"] >= F.col("t_start")) & (p["r"] <= F.col("t_end"))
    cnt = F.aggregate("pts", F.lit(0).cast("long"), lambda acc, p: acc + F.when(inside(p), p["w"]).otherwise(0))
    return near.select("window_id", *keys, cnt.alias("cnt")).where("cnt <> 0")


def rectangles(points: DataFrame, boxes: DataFrame) -> DataFrame:
    """box_id, cnt of points with l in [l1, l2] and r in [r1, r2]; closed."""
    inside = F.col("l").between(F.col("l1"), F.col("l2")) & F.col("r").between(F.col("r1"), F.col("r2"))
    counted = points.join(F.broadcast(boxes), inside).groupBy("box_id").agg(F.sum("w").alias("cnt"))
    return boxes.join(counted, "box_id", "left").select(*boxes.columns, F.coalesce("cnt", F.lit(0)).alias("cnt"))


def count(points: DataFrame, windows: DataFrame, layout: str = "scan") -> DataFrame:
    """window_id, t_start, t_end, cnt by the named layout."""
    if layout not in LAYOUTS:
        raise ValueError(f"layouts are {', '.join(LAYOUTS)}")
    return all_windows(windows, {"scan": scan, "grid": grid, "dyadic": dyadic, "sweep": sweep}[layout](points, windows))
