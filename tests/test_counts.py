"""Indexes against brute force on random graphs and against recorded counts of the given tables."""

import random
from collections import defaultdict
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from bflyspark.functions.hashing import portable_hash
from bflyspark.operators import apps, baselines, dominance, duration, hardness, indexes, measures
from bflyspark.operators.dominance import merge_tree_counts
from bflyspark.sources import catalog, graph, store, windows

GOLDEN = {"g2": [273554, 4842, 4554, 430, 7085, 1], "g4": [584271, 63590, 56357, 11949], "g5": [3392, 339, 321, 87]}


def brute(rows, spans):
    out = []
    for a, b in spans:
        near = defaultdict(set)
        for u, v, t in rows:
            if a <= t <= b:
                near[u].add(v)
        n = 0
        for x, y in combinations(near, 2):
            c = len(near[x] & near[y])
            n += c * (c - 1) // 2
        out.append(n)
    return out


def counts(frame):
    return [r.butterflies for r in frame.orderBy("window_id").collect()]


@pytest.mark.parametrize("seed", [1, 2])
def test_random_graphs_with_repeats(spark, seed):
    rnd = random.Random(seed)
    rows = [(rnd.randint(1, 9), rnd.randint(1, 7), rnd.randint(-5, 25)) for _ in range(110)]
    spans = [(-5, 25), (0, 10), (3, 3), (7, 25), (-5, 4), (30, 40)]
    g, w, want = catalog.literal(spark, rows), windows.fixed(spark, spans), brute(rows, spans)
    assert counts(baselines.recount(g, w)) == want
    assert counts(indexes.query_grouped(indexes.build_grouped(g), w)) == want
    for swap in (g, g.swapped()):
        assert counts(indexes.query_hybrid(indexes.build_hybrid(swap, alpha=0.4), w)) == want
    points = indexes.build_enumerated(g).points.persist()
    for layout in dominance.LAYOUTS:
        assert [r.cnt for r in dominance.count(points, w, layout).orderBy("window_id").collect()] == want, layout
    shifted = catalog.literal(spark, [(u, v, t + 100) for u, v, t in rows])
    assert counts(baselines.recount(shifted, windows.fixed(spark, [(a + 100, b + 100) for a, b in spans]))) == want


@pytest.mark.parametrize("name", sorted(GOLDEN))
def test_recorded_counts(spark, small, name):
    g, w = catalog.load(spark, small, name), windows.fixed(spark, windows.FIXED_DAYS)
    assert counts(indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.5), w))[: len(GOLDEN[name])] == GOLDEN[name]


def test_instance_counts(spark, small):
    g = catalog.load(spark, small, "g9")
    got = counts(duration.instance_counts(g, windows.fixed(spark, [(0, 719), (0, 167), (24, 47)])))
    assert got == [32496598, 130247, 81]


def test_durations(spark, small):
    g = catalog.load(spark, small, "g2")
    deltas = spark.createDataFrame([(90,), (365,), (730,)], "delta long")
    for got in (duration.grouped(g, deltas), duration.query_spans(duration.build_spans(g), deltas), duration.hybrid(g, deltas)):
        assert [r.butterflies for r in got.orderBy("delta").collect()] == [56, 4019, 29949]


def test_timed_butterflies_with_ties(spark):
    rnd = random.Random(4)
    rows = list({(rnd.randint(1, 6), rnd.randint(1, 6), rnd.randint(1, 12)) for _ in range(55)})
    want = defaultdict(int)
    for (u1, v1, a), (u1b, v2, b), (u2, v1b, c), (u2b, v2b, d) in ((p, q, r, s) for p in rows for q in rows if q[0] == p[0] and p[1] < q[1] for r in rows if r[1] == p[1] and r[0] > p[0] for s in rows if s[0] == r[0] and s[1] == q[1]):
        if len({a, b, c, d}) == 4:
            for delta in (3, 6, 11):
                want[delta] += max(a, b, c, d) - min(a, b, c, d) <= delta
    g, deltas = catalog.literal(spark, rows), spark.createDataFrame([(3,), (6,), (11,)], "delta long")
    for side in "uv":
        got = {r.delta: r.butterflies for r in duration.grouped(g, deltas, side).collect()}
        assert got == dict(want)


def test_sampling_is_unbiased(spark, small):
    g, w = catalog.load(spark, small, "g5"), windows.fixed(spark, [(0, 2404)])
    exact = counts(baselines.recount(g, w))[0]
    whole = indexes.query_sampled(indexes.build_sampled(g, 0.5, 1.0, 1.0), w).first()
    assert whole.estimate == exact and whole.std_error == 0
    stairs = indexes.with_stairs(indexes.priority_wedges(g)).persist()
    got = [indexes.thin_butterflies(stairs, 0.2, seed).count() / 0.2 for seed in range(12)]
    mean = sum(got) / len(got)
    assert abs(mean - exact) < 4 * (exact * 0.8 / 0.2 / len(got)) ** 0.5


def test_portable_hash_spreads(spark):
    df = spark.range(20000).select(portable_hash([F.col("id"), F.col("id") % 97], 3).alias("h"))
    share = df.where("h < 300000").count() / 20000
    assert abs(share - 0.3) < 0.02


def test_pair_sampling_comes_near(spark, small):
    g, w = catalog.load(spark, small, "g1"), windows.fixed(spark, [(0, 729)])
    got = baselines.pair_sampling(g, w, 20000).first().estimate
    assert abs(got - 112079) < 0.1 * 112079
    values = baselines.sampled_pairs(g, w, 2000)
    assert baselines.draws_to_error(values, baselines.recount(g, w)).first().draws >= 1


def test_clustering_and_case_study(spark, small):
    g = catalog.load(spark, small, "g2")
    w = windows.fixed(spark, [(1000, 1300)])
    assert measures.three_paths(g, w).first().three_paths == 35438
    row = measures.bcc(indexes.build_hybrid(g, alpha=0.5), g, w).first()
    assert 0 <= row.bcc <= 1 and abs(row.bcc - 4 * 430 / 35438) < 1e-6
    n = apps.busiest_window(spark, g, 7, 0, 1675, 730, 100).first()
    assert n.butterflies >= 0


def test_counters(spark, small):
    row = measures.work_counters(catalog.load(spark, small, "g2")).first()
    assert (row.wedges, row.groups, row.largest, row.butterflies) == (84184, 20326, 26, 273554)
    census = graph.census(catalog.load(spark, small, "g1")).first()
    assert census.pairs == 1444 and abs(census.mean_min_degree - 9.72) < 0.01


def test_index_round_trip(spark, small, tmp_path):
    g, w = catalog.load(spark, small, "g4"), windows.fixed(spark, windows.FIXED_DAYS)
    store.save(indexes.build_hybrid(g, alpha=0.5), str(tmp_path / "index"))
    index = store.load(spark, str(tmp_path / "index"))
    assert counts(indexes.query_hybrid(index, w))[:4] == GOLDEN["g4"]
    plan = store.points_from(index, 1500)._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(part_l" in plan


def test_generated_degrees(spark):
    g = hardness.power_law(spark, 3000, 3000, 2.5, 2.5, 200, 200, seed=3)
    row = hardness.balance(g).first()
    assert row.sum_u == row.sum_v and row.max_u > 20
    even = hardness.balance(hardness.power_law(spark, 3000, 300, 2.1, 0.0, 200, 200, seed=3)).first()
    assert even.max_v < 5 * even.sum_v / 300


def test_merge_tree():
    import numpy as np

    rng = np.random.default_rng(1)
    l = rng.integers(0, 50, 300)  # noqa: E741
    r = l + rng.integers(0, 50, 300)
    w = rng.integers(-2, 4, 300)
    start, end = rng.integers(-5, 60, 80), rng.integers(-5, 110, 80)
    got = merge_tree_counts(l, r, w, start, end)
    assert got.tolist() == [int(w[(l >= a) & (r <= b)].sum()) for a, b in zip(start, end, strict=True)]


def test_duration_kernels_agree():
    """Pairs, look-ups in a tree and the definition, on groups with ties."""
    import numpy as np

    rng = np.random.default_rng(5)
    n = 400
    group, y, l = rng.integers(0, 5, n), rng.integers(0, 9, n), rng.integers(0, 60, n)  # noqa: E741
    r, w, own = l + rng.integers(1, 25, n), rng.integers(1, 4, n), rng.random(n) < 0.7
    deltas = np.array([3, 10, 30, 70])
    rows = list(zip(group.tolist(), y.tolist(), l.tolist(), r.tolist(), w.tolist(), own.tolist(), strict=True))
    want = [sum(a[4] * b[4] for a in rows if a[5] for b in rows if b[0] == a[0] and b[1] != a[1] and b[2] > a[2] and b[2] != a[3] and b[3] != a[3] and max(a[3], b[3]) - a[2] <= d) for d in deltas.tolist()]
    assert duration.near_pairs(group, y, l, r, w, own, deltas).tolist() == want
    order = np.lexsort((y, group))
    every = duration.later_wedges(group[order], l[order], r[order], w[order], own[order], deltas)
    _, both = np.unique(group[order] * 100 + y[order], return_inverse=True)
    assert (every - duration.later_wedges(both, l[order], r[order], w[order], own[order], deltas)).tolist() == want


def test_appended_batches_make_the_full_index(spark):
    """Random batches with repeated and late edges: the points add up to those of a full build, and a batch reads changed wedges alone."""
    from bflyspark.streaming import maintenance

    rnd = random.Random(8)
    rows = [(rnd.randint(1, 8), rnd.randint(1, 6), rnd.randint(0, 20)) for _ in range(60)]
    state = maintenance.empty(spark)
    for k, part in enumerate((rows[:25], rows[25:30], rows[28:60])):
        state, _ = maintenance.append(state, catalog.literal(spark, part).edges, f"t{k}")
    spans = [(0, 20), (3, 9), (8, 20), (5, 5)]
    assert counts(maintenance.counts(state, windows.fixed(spark, spans))) == brute(rows, spans)
    full = indexes.build_enumerated(catalog.literal(spark, rows)).points
    assert sum(r.w for r in state.points.collect()) == sum(r.w for r in full.collect())
    again, added = maintenance.append(state, catalog.literal(spark, rows[:10]).edges, "again")
    assert added.count() == 0


def test_two_sided_sampling_is_unbiased(spark, small):
    g, w = catalog.load(spark, small, "g6"), windows.fixed(spark, [(0, 719)])
    exact = counts(baselines.recount(g, w))[0]
    got = [indexes.query_sampled(indexes.build_sampled(g, 0.3, 0.5, 0.5, seed), w).first() for seed in range(6)]
    mean, spread = sum(r.estimate for r in got) / len(got), max(r.std_error for r in got)
    assert abs(mean - exact) < 4 * spread / len(got) ** 0.5


def test_generated_graphs(spark):
    """Degrees keep their bounds, times are even, and one seed gives one graph."""
    g = hardness.power_law_arrow(spark, 3000, 3000, 2.5, 2.5, 200, 200, seed=3)
    row = hardness.balance(g).first()
    assert row.sum_u == row.sum_v and 20 < row.max_u <= 201 and row.max_v > 20
    assert hardness.uniformity(g).first().chi_square < 19 + 5 * (2 * 19) ** 0.5
    again = hardness.power_law_arrow(spark, 3000, 3000, 2.5, 2.5, 200, 200, seed=3)
    assert g.edges.exceptAll(again.edges).count() == 0
