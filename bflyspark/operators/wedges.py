"""Wedges by vertex priority, their groups and group points.

A wedge x-y-z has its end x before both others in priority, so each butterfly is made by exactly one
group (x, z). Ends lie on one side; `side` names it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.intervals import choose2, signed_points, wedge_stairs
from ..sources.graph import SIDE_U, SIDE_V, TemporalBipartite, unique_degrees

GROUP = ["side", "x", "z"]
SHARE = 4096  # neighbours of a middle that one task joins; a middle of higher degree is split


def prioritised(pairs: DataFrame, *by: str) -> DataFrame:
    """Both directions of every pair: side and id of one end (a), id of the other (b), both degrees, and the pair's columns."""
    deg = unique_degrees(pairs, *by)
    du = deg.where(F.col("side") == SIDE_U).select(*by, F.col("id").alias("u"), F.col("deg").alias("du"))
    dv = deg.where(F.col("side") == SIDE_V).select(*by, F.col("id").alias("v"), F.col("deg").alias("dv"))
    full = pairs.join(du, [*by, "u"]).join(dv, [*by, "v"])
    rest = [c for c in pairs.columns if c not in ("u", "v", *by)]
    one = full.select(*by, F.lit(SIDE_U).alias("side"), F.col("u").alias("a"), F.col("v").alias("b"), F.col("du").alias("da"), F.col("dv").alias("db"), *rest)
    two = full.select(*by, F.lit(SIDE_V).alias("side"), F.col("v").alias("a"), F.col("u").alias("b"), F.col("dv").alias("da"), F.col("du").alias("db"), *rest)
    return one.unionByName(two)


def _before(d1: Column, s1: Column, i1: Column, d2: Column, s2: Column, i2: Column) -> Column:
    """Larger degree first, then the right side, then the smaller id, as one flat comparison."""
    return (d1 > d2) | ((d1 == d2) & ((s1 > s2) | ((s1 == s2) & (i1 < i2))))


def priority_wedges(g: TemporalBipartite | None = None, pairs: DataFrame | None = None, by: tuple[str, ...] = (), with_times: bool = True) -> DataFrame:
    """by..., side, x, z, y and the sorted times of both edges. One join on the middle; edges are oriented before it.

    The neighbours z of a middle of high degree are dealt to several tasks; its few ends x of higher
    priority are copied to each.
    """
    pairs = g.pairs if pairs is None else pairs
    arcs = prioritised(pairs, *by)
    times = ["times"] if with_times else []
    last = F.floor((F.col("db") - 1) / SHARE)
    head = arcs.where(_before(F.col("da"), F.col("side"), F.col("a"), F.col("db"), 1 - F.col("side"), F.col("b")))
    head = head.select(*by, "side", F.col("a").alias("x"), F.col("b").alias("y"), F.col("da").alias("dx"), F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("part"), *(F.col(t).alias("times_x") for t in times))
    tail = arcs.select(*by, "side", F.col("a").alias("z"), F.col("b").alias("y"), F.col("da").alias("dz"), F.pmod(F.xxhash64("a"), last + 1).alias("part"), *(F.col(t).alias("times_z") for t in times))
    both = head.join(tail, [*by, "side", "y", "part"])
    both = both.where((F.col("dx") > F.col("dz")) | ((F.col("dx") == F.col("dz")) & (F.col("x") < F.col("z"))))
    return both.select(*by, "side", "x", "z", "y", *(["times_x", "times_z"] if with_times else []))


def one_sided_wedges(g: TemporalBipartite, side: str = "v") -> DataFrame:
    """Wedges whose ends lie on one side, smaller id first; no priority."""
    end, middle = ("v", "u") if side == "v" else ("u", "v")
    pairs = g.pairs
    left = pairs.select(F.col(end).alias("x"), F.col(middle).alias("y"), F.col("times").alias("times_x"))
    right = pairs.select(F.col(end).alias("z"), F.col(middle).alias("y"), F.col("times").alias("times_z"))
    return left.join(right, "y").where("x < z").select(F.lit(SIDE_V if side == "v" else SIDE_U).alias("side"), "x", "z", "y", "times_x", "times_z")


def with_stairs(wedges: DataFrame) -> DataFrame:
    """Adds the wedge's minimal intervals."""
    return wedges.withColumn("stairs", wedge_stairs(F.col("times_x"), F.col("times_z"))).drop("times_x", "times_z")


def group_sizes(wedges: DataFrame) -> DataFrame:
    """Wedges per group of ends. No interval is read for it."""
    return wedges.groupBy(*GROUP).agg(F.count("*").alias("size"))


def group_points(stairs: DataFrame) -> DataFrame:
    """side, x, z, l, r, w: signed points of each group, equal ones added up, zeros dropped."""
    points = stairs.select(*GROUP, F.explode(signed_points(F.col("stairs"))).alias("p"))
    summed = points.groupBy(*GROUP, F.col("p.l").alias("l"), F.col("p.r").alias("r")).agg(F.sum("p.w").alias("w"))
    return summed.where("w <> 0")


def concentration(sizes: DataFrame, below: int = 10) -> DataFrame:
    """size, groups, wedges, butterflies and the share of groups of smaller sizes; one row per size."""
    hist = sizes.groupBy("size").agg(F.count("*").alias("groups"))
    total = hist.agg(F.sum("groups").alias("all_groups"))
    out = hist.crossJoin(F.broadcast(total))
    return out.select("size", "groups", (F.col("size") * F.col("groups")).alias("wedges"), (choose2(F.col("size")) * F.col("groups")).alias("butterflies"), F.round(F.col("groups") / F.col("all_groups"), 6).alias("share"), (F.col("size") < below).alias("is_small"))
