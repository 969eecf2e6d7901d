"""Recount per window, pair sampling, duration-bounded counters, brute force."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from ..functions.intervals import choose2
from ..functions.ranking import running
from ..sources.graph import TemporalBipartite, in_windows, project
from . import lists
from .dominance import all_windows
from .wedges import GROUP, priority_wedges


def recount(g: TemporalBipartite, windows: DataFrame, parallelism: int | None = None, relabel: bool = False) -> DataFrame:
    """Exact: project each window, enumerate its priority wedges, add up C(c, 2). All windows in one job.

    relabel numbers vertices so that important ones come first; counts don't change.
    """
    pairs = project(relabelled(g) if relabel else g, windows)
    if parallelism:
        pairs = pairs.repartition(parallelism, "window_id", "u")
    wedges = priority_wedges(pairs=pairs, by=("window_id",), with_times=False)
    sizes = wedges.groupBy("window_id", *GROUP).agg(F.count("*").alias("c"))
    counts = sizes.groupBy("window_id").agg(F.sum(choose2(F.col("c"))).alias("butterflies"))
    return all_windows(windows, counts, "butterflies")


def recount_by_lists(g: TemporalBipartite, windows: DataFrame) -> DataFrame:
    """The same recount without wedges as rows: a vertex of the k-th of n windows is id * n + k, so that windows share no vertex.

    Ids must keep below 2^62 / n; a larger one fails the query.
    """
    order = [r.window_id for r in windows.select("window_id").distinct().orderBy("window_id").collect()]  # windows are a batch
    if not order:
        return all_windows(windows, windows.select("window_id", F.lit(0).alias("butterflies")), "butterflies")
    n = len(order)
    ranks = g.edges.sparkSession.createDataFrame(list(enumerate(order)), "k long, window_id long")
    inside = in_windows(g.edges, windows).join(F.broadcast(ranks), "window_id")
    name = lambda c: F.when(F.abs(F.col(c)) < (1 << 62) // n, F.col(c) * n + F.col("k")).otherwise(F.raise_error(F.lit("an id is too large for so many windows")))
    edges = inside.select(name("u").cast("long").alias("u"), name("v").cast("long").alias("v"), F.lit(0).cast("long").alias("t"))
    sizes = lists.folded_histogram(lists.build(TemporalBipartite(edges)), n)
    counts = sizes.groupBy("rest").agg(F.sum(choose2(F.col("size")) * F.col("groups")).alias("butterflies"))
    return all_windows(windows, counts.join(F.broadcast(ranks), F.col("rest") == F.col("k")).select("window_id", "butterflies"), "butterflies")


def relabelled(g: TemporalBipartite) -> TemporalBipartite:
    """Ids in order of falling degree. Ranks come from counts per degree and ranks inside a degree, never one global sort."""

    def ranks(side: str) -> DataFrame:
        deg = g.edges.select("u", "v").distinct().groupBy(side).agg(F.count("*").alias("deg"))
        per = deg.groupBy("deg").agg(F.count("*").alias("n"))
        first = per.select("deg", (F.sum("n").over(Window.orderBy(F.desc("deg"))) - F.col("n")).alias("first"))  # a row per degree
        return running(deg, side, by=("deg",)).join(F.broadcast(first), "deg").select(side, (F.col("first") + F.col("before")).cast("long").alias(f"new_{side}"))

    both = g.edges.join(ranks("u"), "u").join(ranks("v"), "v")
    return TemporalBipartite(both.select(F.col("new_u").alias("u"), F.col("new_v").alias("v"), "t"))


def four_way(g: TemporalBipartite, windows: DataFrame) -> DataFrame:
    """Brute force by definition: four projected pairs that close. For small graphs."""
    p = project(g, windows)
    a = p.select("window_id", F.col("u").alias("u1"), F.col("v").alias("v1"))
    b = p.select("window_id", F.col("u").alias("u1"), F.col("v").alias("v2"))
    c = p.select("window_id", F.col("u").alias("u2"), F.col("v").alias("v1"))
    d = p.select("window_id", F.col("u").alias("u2"), F.col("v").alias("v2"))
    closed = a.join(b, ["window_id", "u1"]).where("v1 < v2").join(c, ["window_id", "v1"]).where("u1 < u2").join(d, ["window_id", "u2", "v2"])
    return all_windows(windows, closed.groupBy("window_id").agg(F.count("*").alias("butterflies")), "butterflies")


def sampled_pairs(g: TemporalBipartite, windows: DataFrame, draws: int, side: str = "u", seed: int = 1, weights: str = "degree") -> DataFrame:
    """window_id, draw, value: unbiased single estimates from pairs of vertices of one side.

    Both ends of a pair are drawn by degree (an edge each, with replacement) or evenly. Each vertex owns as
    many numbers of its window as its degree; draws pick numbers by modular arithmetic. A number is looked
    up by the block of ids that holds it, and then by the vertex inside.
    """
    end, other = ("u", "v") if side == "u" else ("v", "u")
    pairs = project(g, windows).select("window_id", F.col(end).alias("e"), F.col(other).alias("o"))
    deg = pairs.groupBy("window_id", "e").agg(F.count("*").alias("deg"))
    own = F.col("deg") if weights == "degree" else F.lit(1).cast("long")
    pool = running(deg, "e", own, ("window_id",)).select("window_id", "e", "deg", (F.col("before") + 1).alias("first"), (F.col("before") + own).alias("last"), F.shiftright("e", 12).alias("block"))
    blocks = pool.groupBy("window_id", "block").agg(F.min("first").alias("first"), F.max("last").alias("last"))
    total = pool.groupBy("window_id").agg(F.max("last").alias("m"))
    asked = total.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(draws)))).withColumn("draw", F.col("draw").cast("long"))
    pick = lambda which: 1 + F.pmod(portable_hash([F.col("draw") * 2 + which, F.col("window_id"), F.col("draw")], seed) * 1009 + portable_hash([F.col("draw") + 7919, F.col("window_id")], seed + 13 + which), F.col("m"))
    asked = asked.withColumn("ka", pick(0)).withColumn("kb", pick(1))

    def owner(rows: DataFrame, number: str, name: str, degree: str) -> DataFrame:
        inside = F.col(number).between(F.col("first"), F.col("last"))
        near = rows.join(blocks, "window_id").where(inside).drop("first", "last")
        return near.join(pool, ["window_id", "block"]).where(inside).drop("first", "last", "block").withColumnsRenamed({"e": name, "deg": degree})

    drawn = owner(owner(asked, "ka", "a", "da"), "kb", "b", "db")
    near_a = pairs.select("window_id", F.col("e").alias("a"), "o")
    near_b = pairs.select("window_id", F.col("e").alias("b"), "o")
    common = drawn.where("a <> b").join(near_a, ["window_id", "a"]).join(near_b, ["window_id", "b", "o"]).groupBy("window_id", "draw").agg(F.count("*").alias("c"))
    out = drawn.join(common, ["window_id", "draw"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    m = F.col("m").cast("double")
    scale = m * m / (2 * F.col("da") * F.col("db")) if weights == "degree" else m * m / 2
    return out.select("window_id", "draw", F.when(F.col("a") == F.col("b"), F.lit(0.0)).otherwise(scale * choose2(F.col("c"))).alias("value"))


def pair_sampling(g: TemporalBipartite, windows: DataFrame, draws: int, side: str = "u", seed: int = 1, weights: str = "degree") -> DataFrame:
    """window_id, estimate over all draws."""
    values = sampled_pairs(g, windows, draws, side, seed, weights)
    mean = values.groupBy("window_id").agg(F.round(F.avg("value"), 6).alias("estimate"))
    return windows.join(mean, "window_id", "left").select("window_id", "t_start", "t_end", F.coalesce("estimate", F.lit(0.0)).alias("estimate"))


def draws_to_error(values: DataFrame, exact: DataFrame, target: float = 0.1) -> DataFrame:
    """window_id and the first draw at which the running mean is within target of the exact count (null: never)."""
    running = values.withColumn("mean", F.avg("value").over(Window.partitionBy("window_id").orderBy("draw").rowsBetween(Window.unboundedPreceding, 0)))
    both = running.join(exact.select("window_id", "butterflies"), "window_id")
    error = F.abs(F.col("mean") - F.col("butterflies")) / F.col("butterflies")
    return both.groupBy("window_id").agg(F.min(F.when(error <= target, F.col("draw"))).alias("draws"))


# Duration-bounded butterflies: four edges of strictly increasing times that span at most delta.


def instance_wedges(g: TemporalBipartite, delta: int | None = None, side: str = "v") -> DataFrame:
    """x, z, y, l, r: pairs of edges at one middle with different times, ends on one side, smaller id first."""
    end, middle = ("v", "u") if side == "v" else ("u", "v")
    e = g.edges.distinct()
    a = e.select(F.col(end).alias("x"), F.col(middle).alias("y"), F.col("t").alias("tx"))
    b = e.select(F.col(end).alias("z"), F.col(middle).alias("y"), F.col("t").alias("tz"))
    both = a.join(b, "y").where("x < z and tx <> tz")
    both = both.select("x", "z", "y", F.least("tx", "tz").alias("l"), F.greatest("tx", "tz").alias("r"))
    return both if delta is None else both.where(F.col("r") - F.col("l") <= delta)


def timed_butterflies(g: TemporalBipartite, delta: int | None = None, side: str = "v") -> DataFrame:
    """x, z, y1, y2, l, r, one row each."""
    w = instance_wedges(g, delta, side)
    a = w.select("x", "z", F.col("y").alias("y1"), F.col("l").alias("l1"), F.col("r").alias("r1"))
    b = w.select("x", "z", F.col("y").alias("y2"), F.col("l").alias("l2"), F.col("r").alias("r2"))
    both = a.join(b, ["x", "z"]).where("y1 < y2 and l1 <> l2 and l1 <> r2 and r1 <> l2 and r1 <> r2")
    out = both.select("x", "z", "y1", "y2", F.least("l1", "l2").alias("l"), F.greatest("r1", "r2").alias("r"))
    return out if delta is None else out.where(F.col("r") - F.col("l") <= delta)


def duration_count(g: TemporalBipartite, delta: int, side: str = "v") -> DataFrame:
    """delta, butterflies: counted from scratch for one delta."""
    n = timed_butterflies(g, delta, side).agg(F.count("*").alias("butterflies"))
    return n.select(F.lit(delta).cast("long").alias("delta"), "butterflies")


def duration_list(g: TemporalBipartite, delta: int, limit: int | None = None, side: str = "v") -> DataFrame:
    """The butterflies themselves, in order; only a limit makes it short."""
    rows = timed_butterflies(g, delta, side)
    return rows if limit is None else rows.orderBy("l", "r", "x", "z", "y1", "y2").limit(limit)


def duration_per_window(g: TemporalBipartite, windows: DataFrame, side: str = "v") -> DataFrame:
    """The duration counter reused for windows: time-ordered butterflies inside each window, all windows in one job."""
    inside = (F.col("l") >= F.col("t_start")) & (F.col("r") <= F.col("t_end"))
    counts = timed_butterflies(g, None, side).join(F.broadcast(windows), inside).groupBy("window_id").agg(F.count("*").alias("butterflies"))
    return all_windows(windows, counts, "butterflies")
