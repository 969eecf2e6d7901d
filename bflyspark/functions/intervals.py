"""Active intervals of wedges and butterflies, and signed points for repeated edges.

An interval is struct<l, r>. An edge that occurs several times gives a subgraph several minimal
intervals (a staircase: both ends strictly rise). Weights +1 at each (l_i, r_i) and -1 at each
(l_i, r_{i+1}) add up to 1 inside any window that holds one of them, and to 0 in all others.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

INTERVAL = "struct<l:bigint,r:bigint>"
POINT = "struct<l:bigint,r:bigint,w:bigint>"


def interval(l: Column, r: Column) -> Column:  # noqa: E741
    return F.struct(l.cast("long").alias("l"), r.cast("long").alias("r"))


def wedge_interval(t1: Column, t2: Column) -> Column:
    """Of a wedge whose edges have one time each."""
    return interval(F.least(t1, t2), F.greatest(t1, t2))


def compose(a: Column, b: Column) -> Column:
    """Smallest interval that holds both."""
    return interval(F.least(a["l"], b["l"]), F.greatest(a["r"], b["r"]))


def bound(value: Column, body) -> Column:
    """body(value), with the value computed once per row: in there it is a variable of a lambda."""
    return F.transform(F.array(value), body)[0]


def merged_stairs(a: Column, b: Column) -> Column:
    """Minimal intervals that hold one of a and one of b, in one merge of two staircases.

    A start l asks for the least r: the larger of the ends of the first steps of a and b from l on. In the
    order of starts the k-th entry, if it is the i-th of its own staircase, has k - i of the other before
    it, so both steps are found by place. A start counts if no later one has the same r, and if no entry
    with the same start has a smaller one.
    """

    def entries(stairs: Column, source: int) -> Column:
        return F.transform(stairs, lambda s, i: F.struct(s["l"].alias("l"), F.lit(source).alias("source"), i.alias("place")))

    def merge(a: Column, b: Column) -> Column:
        def least_end(e: Column, k: Column) -> Column:
            own, other = e["place"], k - e["place"]
            first = F.get(a, F.when(e["source"] == 0, own).otherwise(other))["r"]
            second = F.get(b, F.when(e["source"] == 0, other).otherwise(own))["r"]
            return F.struct(e["l"].alias("l"), F.when(first.isNotNull() & second.isNotNull(), F.greatest(first, second)).alias("r"))

        def kept(steps: Column) -> Column:
            later, earlier = lambda k: F.get(steps, k + 1), lambda k: F.get(steps, k - 1)
            falls = lambda s, k: later(k)["r"].isNull() | (s["r"] < later(k)["r"])
            beaten = lambda s, k: F.coalesce((earlier(k)["l"] == s["l"]) & (earlier(k)["r"] < s["r"]), F.lit(False))
            return F.filter(steps, lambda s, k: s["r"].isNotNull() & falls(s, k) & ~beaten(s, k))

        order = F.array_sort(F.concat(entries(a, 0), entries(b, 1)))
        return bound(order, lambda m: bound(F.transform(m, least_end), kept))

    return bound(a, lambda x: bound(b, lambda y: merge(x, y))).cast(f"array<{INTERVAL}>")


def wedge_stairs(times1: Column, times2: Column) -> Column:
    """Minimal intervals of a wedge from the sorted times of its two edges; an edge's times are a staircase of points."""
    simple = (F.size(times1) == 1) & (F.size(times2) == 1)
    steps = lambda times: F.transform(times, lambda t: interval(t, t))
    return F.when(simple, F.array(wedge_interval(times1[0], times2[0]))).otherwise(merged_stairs(steps(times1), steps(times2)))


def compose_stairs(a: Column, b: Column) -> Column:
    """Minimal intervals of a butterfly from those of its two wedges."""
    simple = (F.size(a) == 1) & (F.size(b) == 1)
    return F.when(simple, F.array(compose(a[0], b[0]))).otherwise(merged_stairs(a, b))


def signed_points(stairs: Column) -> Column:
    """array<struct<l, r, w>> of a staircase."""
    plus = F.transform(stairs, lambda s: F.struct(s["l"].alias("l"), s["r"].alias("r"), F.lit(1).cast("long").alias("w")))
    n = F.size(stairs)
    minus = F.zip_with(F.slice(stairs, 1, F.greatest(n - 1, F.lit(0))), F.slice(stairs, 2, F.greatest(n - 1, F.lit(0))), lambda a, b: F.struct(a["l"].alias("l"), b["r"].alias("r"), F.lit(-1).cast("long").alias("w")))
    return F.when(n > 1, F.concat(plus, minus)).otherwise(plus)


def choose2(c: Column) -> Column:
    """c over 2, in whole numbers."""
    return F.shiftright(c * (c - 1), 1)


def active_interval(edges: DataFrame, *by: str) -> DataFrame:
    """Earliest and latest time of each subgraph's edges."""
    return edges.groupBy(*by).agg(F.min("t").alias("l"), F.max("t").alias("r"))
