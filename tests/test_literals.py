"""Worked examples and graphs of known counts."""

import random

import pytest
from pyspark.sql import functions as F

from bflyspark.functions.intervals import compose, compose_stairs, wedge_interval, wedge_stairs
from bflyspark.operators import baselines, dominance, duration, hardness, indexes
from bflyspark.operators.wedges import GROUP, group_points, group_sizes, priority_wedges, with_stairs
from bflyspark.sources import catalog, windows
from bflyspark.sources.graph import from_table


def counts(frame):
    return [r.butterflies for r in frame.orderBy("window_id").collect()]


def every_method(g, w):
    yield "recount", counts(baselines.recount(g, w))
    yield "relabelled", counts(baselines.recount(g, w, relabel=True))
    yield "four-way", counts(baselines.four_way(g, w))
    yield "enumerated", counts(indexes.query_enumerated(indexes.build_enumerated(g), w))
    yield "grouped", counts(indexes.query_grouped(indexes.build_grouped(g), w))
    yield "packed", counts(indexes.query_grouped(indexes.build_grouped(g), w, "packed"))
    for alpha in (0.0, 0.5, 1.0):
        yield f"hybrid {alpha}", counts(indexes.query_hybrid(indexes.build_hybrid(g, alpha=alpha), w))


def test_toy_graph(spark):
    g = catalog.literal(spark, catalog.TOY)
    w = windows.fixed(spark, [(1, 5), (1, 6), (2, 4), (4, 6), (3, 6), (5, 6)])
    for name, got in every_method(g, w):
        assert got == [1, 3, 1, 1, 1, 0], name
    points = {(r.l, r.r): r.w for r in indexes.build_enumerated(g).points.collect()}
    assert points == {(2, 4): 1, (2, 6): 1, (4, 6): 1}
    wedges = with_stairs(priority_wedges(g)).collect()
    assert {(r.x, r.z) for r in wedges} == {(4, 5)}
    assert sorted((s.l, s.r) for r in wedges for s in r.stairs) == [(2, 3), (4, 4), (5, 6)]


def test_wedge_and_butterfly_intervals(spark):
    row = spark.range(1).select(wedge_interval(F.lit(1), F.lit(3)).alias("a"), wedge_interval(F.lit(4), F.lit(2)).alias("b"))
    row = row.select("a", "b", compose(F.col("a"), F.col("b")).alias("c")).first()
    assert tuple(row.a) == (1, 3) and tuple(row.b) == (2, 4) and tuple(row.c) == (1, 4)


def test_repeated_edges(spark):
    g = catalog.literal(spark, catalog.DUPLICATES)
    w = windows.fixed(spark, [(1, 8), (2, 9), (1, 9), (2, 8)])
    for name, got in every_method(g, w):
        assert got == [1, 1, 1, 0], name
    points = {(r.l, r.r): r.w for r in indexes.build_enumerated(g).points.collect()}
    assert points == {(1, 8): 1, (2, 9): 1, (1, 9): -1}
    twice = from_table(g.edges.union(g.edges))
    assert counts(baselines.recount(twice, w)) == [1, 1, 1, 0]


def test_minimal_intervals(spark):
    row = spark.range(1).select(wedge_stairs(F.array(*map(F.lit, (1, 5, 9))), F.array(*map(F.lit, (2, 8)))).alias("s")).first()
    assert [tuple(x) for x in row.s] == [(1, 2), (2, 5), (5, 8), (8, 9)]
    none = F.array().cast("array<struct<l:bigint,r:bigint>>")
    assert spark.range(1).select(compose_stairs(none, none).alias("s")).first().s == []


def least(candidates):
    """Those that hold no other one, by definition."""
    kinds = set(candidates)
    return sorted(c for c in kinds if not any(d != c and c[0] <= d[0] and d[1] <= c[1] for d in kinds))


def test_stairs_of_random_times(spark):
    """Wedges of repeated edges and butterflies of such wedges against all pairs, with ties."""
    rnd = random.Random(6)
    rows = [(i, *(sorted(rnd.sample(range(20), rnd.randint(1, 9))) for _ in range(4))) for i in range(300)]
    df = spark.createDataFrame(rows, "i long, a array<long>, b array<long>, c array<long>, d array<long>")
    wedges = df.select("*", wedge_stairs(F.col("a"), F.col("b")).alias("p"), wedge_stairs(F.col("c"), F.col("d")).alias("q"))
    for r in wedges.select("*", compose_stairs(F.col("p"), F.col("q")).alias("s")).collect():
        p, q = ([tuple(x) for x in side] for side in (r.p, r.q))
        assert p == least([(min(x, y), max(x, y)) for x in r.a for y in r.b])
        assert q == least([(min(x, y), max(x, y)) for x in r.c for y in r.d])
        assert [tuple(x) for x in r.s] == least([(min(x[0], y[0]), max(x[1], y[1])) for x in p for y in q])


def test_set_disjointness(spark):
    sets = spark.createDataFrame([(1, 1), (1, 2), (2, 2), (2, 3), (3, 3), (3, 4)], "set_id long, element long")
    g = hardness.reduce_sets(sets)
    w = windows.fixed(spark, [(1, 2), (2, 3), (1, 3), (2, 2)])
    assert counts(baselines.recount(g, w)) == [1, 1, 2, 0]
    for a, b, common in ((1, 2, 1), (2, 3, 1), (1, 3, 0)):
        got = hardness.intersection_size(baselines.recount(g, hardness.intersection_windows(spark, a, b))).first()
        assert got.common == common


def split_example(spark):
    """Groups of 100, 50 and, in small ones, 97 wedges that make 50 butterflies."""
    rows, nxt, end = [], 10_000, 1
    for size, times in ((100, 1), (50, 1), (10, 1), (2, 5), (1, 77)):
        for _ in range(times):
            for _ in range(size):
                rows += [(end, nxt, nxt % 50), (end + 1, nxt, nxt % 37)]
                nxt += 1
            end += 2
    return catalog.literal(spark, rows)


def test_split_by_share(spark):
    g = split_example(spark)
    sizes = group_sizes(priority_wedges(g)).persist()
    hist = {r["size"]: (r["groups"], r["butterflies"]) for r in indexes.size_histogram(sizes).collect()}
    assert hist[100] == (1, 4950) and hist[50] == (1, 1225) and hist[10] == (1, 45) and hist[2] == (5, 5)
    cut = indexes.cutoff_by_share(sizes, 0.1)
    small, large = indexes.split_groups(sizes, cut)
    assert large.count() == 2 and small.count() == 6
    assert cut.size == 10 and abs(cut.alpha - 50 / 6225) < 1e-9
    assert indexes.cutoff_by_share(sizes, 0.0).alpha == 0.0
    assert indexes.cutoff_by_share(sizes, 1.0).alpha == 1.0
    assert indexes.cutoff_by_share(sizes, 1.0, rule="below").size == 50
    w = windows.fixed(spark, [(0, 60)])
    for alpha in (0.0, 0.1, 1.0):
        for rule in ("atmost", "below"):
            for ties in ("class", "exact"):
                assert counts(indexes.query_hybrid(indexes.build_hybrid(g, alpha=alpha, rule=rule, ties=ties), w)) == [6225]


def test_memory_limit_walks_from_small_groups(spark):
    sizes = group_sizes(priority_wedges(split_example(spark))).persist()
    free, tight = indexes.cutoff_by_memory(sizes, 10**9), indexes.cutoff_by_memory(sizes, 1)
    assert free.alpha == 1.0 and tight.alpha < 0.01
    levels = [indexes.cutoff_by_memory(sizes, b).alpha for b in (1, 10_000, 50_000, 150_000)]
    assert levels == sorted(levels)


@pytest.mark.parametrize("a,b", [(4, 5), (2, 2), (1, 6)])
def test_complete_graphs(spark, a, b):
    g = catalog.literal(spark, [(u, v, 3) for u in range(a) for v in range(b)])
    want = a * (a - 1) // 2 * (b * (b - 1) // 2)
    for name, got in every_method(g, windows.fixed(spark, [(3, 3), (4, 9)])):
        assert got == [want, 0], name


def test_graphs_without_butterflies(spark):
    for rows in ([(1, v, v) for v in range(6)], [(1, 1, 1), (1, 2, 2), (2, 2, 3), (2, 3, 4)], []):
        g = catalog.literal(spark, rows)
        w = windows.fixed(spark, [(0, 100)])
        assert counts(baselines.recount(g, w)) == [0]
        assert counts(indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.5), w)) == [0]
        assert [r.cnt for r in dominance.count(indexes.build_enumerated(g).points, w, "dyadic").collect()] == [0]


def test_sides_with_equal_ids_stay_apart(spark):
    g = catalog.literal(spark, [(1, 1, 1), (1, 2, 2), (2, 1, 3), (2, 2, 4)])
    for name, got in every_method(g, windows.fixed(spark, [(1, 4), (2, 4), (-5, 9)])):
        assert got == [1, 0, 1], name


def test_strictly_ordered_times(spark):
    deltas = spark.createDataFrame([(4,), (5,), (100,)], "delta long")
    tied = catalog.literal(spark, [(1, 1, 1), (1, 2, 1), (2, 1, 3), (2, 2, 6)])
    free = catalog.literal(spark, [(1, 1, 1), (1, 2, 2), (2, 1, 3), (2, 2, 6)])
    for g, want in ((tied, [0, 0, 0]), (free, [0, 1, 1])):
        for got in (duration.query_spans(duration.build_spans(g), deltas), duration.grouped(g, deltas), duration.hybrid(g, deltas, 1), duration.hybrid(g, deltas)):
            assert [r.butterflies for r in got.orderBy("delta").collect()] == want
        assert [baselines.duration_count(g, d).first().butterflies for d in (4, 5, 100)] == want


def test_null_edges_fail(spark):
    g = from_table(spark.createDataFrame([(1, None, 3)], "u long, v long, t long"))
    with pytest.raises(Exception, match="null"):
        g.edges.collect()


def test_group_points_add_up(spark):
    g = catalog.literal(spark, catalog.TOY)
    rows = group_points(with_stairs(priority_wedges(g))).select(*GROUP, "l", "r", "w").collect()
    assert sum(r.w for r in rows) == 3
