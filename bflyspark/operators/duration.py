"""Indexes for many duration thresholds: built once up to a largest span, asked for any batch of smaller ones.

A butterfly in time order is two wedges of one pair of ends, with other middles and four different times,
that span at most delta. Small groups are enumerated: how many butterflies span exactly so much. Large
groups stay as packed lists (lists.py), cut by stretches of time as long as the largest span, so that a group of
any size is read by many tasks; each wedge asks how many wedges that begin after it end in time, from a merge
tree or, in a stretch of few wedges, by its pairs. No wedge is shuffled or stored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.intervals import choose2
from ..sources.graph import TemporalBipartite, in_windows
from ..sources.scratch import written
from . import lists
from .baselines import timed_butterflies
from .dominance import merge_tree_counts
from .indexes import Cutoff, cutoff_by_share

PAIRED = 2048  # points of a group up to which its pairs are read one by one; beyond, look-ups in a tree are fewer
ASKED = 1 << 20  # look-ups at once


@dataclass(frozen=True)
class DurationIndex:
    """spans: span, n of the enumerated part. lists: all groups packed; those of more than meta["size"] wedges in a stretch are the grouped part."""

    spans: DataFrame
    lists: DataFrame
    meta: dict = field(default_factory=dict)


def build_spans(g: TemporalBipartite, side: str = "v", largest: int | None = None) -> DataFrame:
    """span, n: how many butterflies span exactly so much, up to the largest. The enumerated part's index."""
    return timed_butterflies(g, largest, side).groupBy((F.col("r") - F.col("l")).alias("span")).agg(F.count("*").alias("n"))


def query_spans(spans: DataFrame, deltas: DataFrame) -> DataFrame:
    """delta, butterflies for every delta; spans are few."""
    inside = deltas.join(spans, F.col("span") <= F.col("delta"), "left")
    return inside.groupBy("delta").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("butterflies"))


def spans_of(packed: DataFrame, largest: int, most: int, turns: int) -> DataFrame:
    """The span histogram of the groups of most wedges at most in a stretch, no longer than the largest."""

    def solve(stretches):
        for s in stretches:
            ones = np.ones(len(s.l), np.int64)
            found = [np.unique(span, return_counts=True) for span, _ in pair_spans(s.group, s.y, s.l, s.r, ones, s.own, largest)]
            if found:
                span, n = (np.concatenate(c) for c in zip(*found, strict=True))
                span, at = np.unique(span, return_inverse=True)
                total = np.zeros(len(span), np.int64)
                np.add.at(total, at, n)
                yield span, total

    return lists.map_stretches(packed, solve, "span n", 2, most, largest, turns).groupBy("span").agg(F.sum("n").alias("n"))


def stretch_sizes(packed: DataFrame, largest: int, turns: int) -> DataFrame:
    """size, groups: how many groups have so many wedges in a stretch."""

    def solve(stretches):
        for s in stretches:
            yield np.unique(s.size, return_counts=True)

    return lists.map_stretches(packed, solve, "size groups", 2, None, largest, turns).groupBy("size").agg(F.sum("groups").alias("groups"))


def build(g: TemporalBipartite, largest: int, alpha: float = 0.5, side: str = "v") -> DurationIndex:
    """Both parts of the index, written once. Wedges longer than the largest span belong to no butterfly that is asked for.

    Ends come before middles in priority; of two vertices of one degree, that of the side named does.
    """
    packed = lists.build(g if side == "v" else g.swapped())
    turns = lists.turns(packed)
    cutoff = cutoff_by_share(stretch_sizes(packed, largest, turns), alpha) if alpha > 0 else Cutoff(1, 0, 0.0, 0)
    spans = g.edges.sparkSession.createDataFrame([], "span long, n long")
    if cutoff.size > 1:
        spans = written(spans_of(packed, largest, cutoff.size, turns), "duration-spans")
    return DurationIndex(spans, packed, {"largest": largest, "alpha": cutoff.alpha, "size": max(1, cutoff.size), "turns": turns})


def later_wedges(group: np.ndarray, l: np.ndarray, r: np.ndarray, w: np.ndarray, asks: np.ndarray, deltas: np.ndarray) -> np.ndarray:  # noqa: E741
    """Per delta: pairs of a point that asks and a point of its group that begins later, no time shared, both within delta.

    Groups are laid behind one another on the line of time, too far apart to meet.
    """
    reach = int(deltas.max()) + 1
    low = int(l.min())
    width = int(r.max()) - low + reach + 2
    base = group.astype(np.int64) * width - low
    l, r = l + base, r + base  # noqa: E741
    times = np.unique(np.concatenate([l, r]))
    rank = lambda x: np.searchsorted(times, x)
    stride = len(times) + 1

    def summed(first: np.ndarray, second: np.ndarray):
        """Weight of points with a given first time and a second one in [low rank, high rank)."""
        key = rank(first) * stride + rank(second)
        order = np.argsort(key, kind="stable")
        key, total = key[order], np.concatenate([[0], np.cumsum(w[order])])
        return lambda at, a, b: total[np.searchsorted(key, rank(at) * stride + b)] - total[np.searchsorted(key, rank(at) * stride + a)]

    by_start, by_end = summed(l, r), summed(r, l)
    out = np.zeros(len(deltas), np.int64)
    for d, delta in enumerate(deltas.tolist()):
        asking = np.flatnonzero(asks & (r - l <= delta))
        for at in range(0, len(asking), ASKED):
            own = asking[at : at + ASKED]
            until = l[own] + delta
            n = merge_tree_counts(l, r, w, l[own] + 1, until)
            past = np.searchsorted(times, until, "right")
            n = n - by_start(r[own], 0, past) - by_end(r[own], rank(l[own]) + 1, stride - 1)
            out[d] += int((w[own] * n).sum())
    return out


def pair_spans(group: np.ndarray, y: np.ndarray, l: np.ndarray, r: np.ndarray, w: np.ndarray, asks: np.ndarray, largest: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:  # noqa: E741
    """Spans up to the largest, and weights, of pairs of two different middles, by the pairs themselves: each point with the k-th after it in its group, for all groups at once.

    Points that lie behind the largest span end the walk of those before them.
    """
    order = np.lexsort((r, l, group))
    group, y, l, r, w, asks = (c[order] for c in (group, y, l, r, w, asks))  # noqa: E741
    i, k = np.flatnonzero(asks & (r - l <= largest)), 1
    while len(i):
        i = i[i + k < len(l)]
        i = i[(group[i + k] == group[i]) & (l[i + k] - l[i] <= largest)]
        j = i + k
        span = np.maximum(r[i], r[j]) - l[i]
        use = (y[i] != y[j]) & (l[i] != l[j]) & (l[j] != r[i]) & (r[i] != r[j]) & (span <= largest)
        yield span[use], w[i[use]] * w[j[use]]
        k += 1


def near_pairs(group: np.ndarray, y: np.ndarray, l: np.ndarray, r: np.ndarray, w: np.ndarray, asks: np.ndarray, deltas: np.ndarray) -> np.ndarray:  # noqa: E741
    """Per delta, the same of two different middles, from the pairs themselves."""
    total = np.zeros(len(deltas), np.int64)
    for span, n in pair_spans(group, y, l, r, w, asks, int(deltas[-1])):
        np.add.at(total, np.searchsorted(deltas, span), n)
    return np.cumsum(total)


def query_points(index: DurationIndex, deltas: DataFrame) -> DataFrame:
    """delta, n of the grouped part: all pairs of a group less those that share their middle. Deltas are a batch on the driver."""
    asked = np.array(sorted({r.delta for r in deltas.collect()}), np.int64)

    def solve(stretches):
        total = np.zeros(len(asked), np.int64)
        for s in stretches if len(asked) else ():
            w = np.ones(len(s.l), np.int64)
            few = np.repeat(s.size <= PAIRED, s.size)
            total += near_pairs(*(c[few] for c in (s.group, s.y, s.l, s.r, w, s.own)), asked)
            if few.all():
                continue
            group, y, l, r, w, own = (c[~few] for c in (s.group, s.y, s.l, s.r, w, s.own))  # noqa: E741
            order = np.lexsort((y, group))
            group, y, l, r, own = (c[order] for c in (group, y, l, r, own))  # noqa: E741
            fresh = np.concatenate([[False], group[1:] != group[:-1]])
            other = fresh | np.concatenate([[False], y[1:] != y[:-1]])
            for names, sign in ((fresh, 1), (other, -1)):
                total += sign * later_wedges(np.cumsum(names), l, r, w, own, asked)
        yield asked, total

    m = index.meta
    return lists.map_stretches(index.lists, solve, "delta part", m["size"] + 1, None, m["largest"], m["turns"]).groupBy("delta").agg(F.sum("part").alias("n"))


def query(index: DurationIndex, deltas: DataFrame) -> DataFrame:
    """delta, butterflies for each delta up to the largest of the index."""
    over = deltas.agg(F.max("delta")).first()[0]
    if over is not None and over > index.meta["largest"]:
        raise ValueError(f"the index holds spans up to {index.meta['largest']}, not {over}")
    large = deltas.distinct().join(query_points(index, deltas), "delta", "left").select("delta", F.coalesce("n", F.lit(0)).alias("butterflies"))
    both = large.unionByName(query_spans(index.spans, deltas.distinct()))
    return both.groupBy("delta").agg(F.sum("butterflies").cast("long").alias("butterflies"))


def largest_of(deltas: DataFrame) -> int:
    return deltas.agg(F.max("delta")).first()[0] or 0


def grouped(g: TemporalBipartite, deltas: DataFrame, side: str = "v") -> DataFrame:
    """All groups by points: built up to the largest delta and asked once."""
    return query(build(g, largest_of(deltas), 0.0, side), deltas)


def hybrid(g: TemporalBipartite, deltas: DataFrame, alpha: float = 0.5, side: str = "v") -> DataFrame:
    """Small groups by spans, large groups by points: built up to the largest delta and asked once."""
    return query(build(g, largest_of(deltas), alpha, side), deltas)


def instance_counts(g: TemporalBipartite, windows: DataFrame, side: str = "v") -> DataFrame:
    """window_id, butterflies: every choice of four temporal edges counts. C(c, 2) per group less C(c_y, 2) per middle."""
    end, middle = ("v", "u") if side == "v" else ("u", "v")
    e = in_windows(g.edges.distinct(), windows).groupBy("window_id", end, middle).agg(F.count("*").alias("k"))
    a = e.select("window_id", F.col(end).alias("x"), F.col(middle).alias("y"), F.col("k").alias("k1"))
    b = e.select("window_id", F.col(end).alias("z"), F.col(middle).alias("y"), F.col("k").alias("k2"))
    c = a.join(b, ["window_id", "y"]).where("x < z").select("window_id", "x", "z", (F.col("k1") * F.col("k2")).alias("c"))
    groups = c.groupBy("window_id", "x", "z").agg(F.sum("c").alias("n"), F.sum(choose2(F.col("c"))).alias("same"))
    counts = groups.groupBy("window_id").agg(F.sum(choose2(F.col("n")) - F.col("same")).alias("butterflies"))
    return windows.join(counts, "window_id", "left").select(*windows.columns, F.coalesce("butterflies", F.lit(0)).cast("long").alias("butterflies"))
