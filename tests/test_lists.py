"""Packed wedge lists against wedges as rows, and what they leave on disk."""

import random
import time
import uuid
from collections import Counter
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from bflyspark.operators import baselines, duration, indexes, lists
from bflyspark.operators.wedges import GROUP, group_points, group_sizes, priority_wedges, with_stairs
from bflyspark.sources import catalog, graph, scratch, windows


@pytest.fixture
def folder(monkeypatch, tmp_path):
    monkeypatch.setattr(scratch, "scratch", lambda spark, label: f"{tmp_path}/{label}-{uuid.uuid4().hex}")
    return tmp_path


@pytest.fixture
def repeated(spark):
    """Edges with up to five times, hubs on both sides, ids of all magnitudes."""
    rnd = random.Random(2)
    name = lambda k: (-1) ** k * (1 << 62) + k if k % 3 == 0 else k
    rows = [(name(int(40 * rnd.random() ** 2)), name(int(30 * rnd.random() ** 2)), rnd.randrange(25)) for _ in range(500)]
    return catalog.literal(spark, rows)


def test_lists_hold_all_groups(spark, monkeypatch, repeated):
    monkeypatch.setattr(lists, "PART", 40)
    packed, wedges = lists.build(repeated), with_stairs(priority_wedges(repeated))
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(lists.histogram(packed)) == rows(group_sizes(wedges).groupBy("size").agg(F.count("*")))
    some = group_sizes(wedges).where("size >= 3")
    assert rows(lists.points(packed, 3)) == rows(group_points(wedges).join(some, GROUP).select(*GROUP, "l", "r", "w", "size"))
    assert rows(lists.enumerated(packed)) == rows(indexes.enumerate_points(group_points(wedges)).select("l", "r", "w"))


def test_ends_of_many_wedges_are_worked_off_in_passes(spark, monkeypatch, repeated):
    packed = [r.data for r in lists.build(repeated).collect()]
    points = lambda: sorted((int(b.x[g]), int(b.z[g]), int(b.times[i]), int(b.times[j]), int(w), int(b.size[g])) for data in packed for b in lists.blocks(data) for g, i, j, w in zip(b.group, b.l, b.r, b.w, strict=True))
    whole = points()
    monkeypatch.setattr(lists, "WEDGES", 30)
    assert len(whole) > 1000 and points() == whole


def test_an_index_leaves_no_wedges_on_disk(spark, folder):
    rnd = random.Random(4)
    g = catalog.literal(spark, [(rnd.randrange(400), rnd.randrange(500), rnd.randrange(1000)) for _ in range(12_000)])
    wedges = priority_wedges(g, with_times=False).count()
    index = indexes.build_hybrid(g, alpha=0.5)
    index.points.count()
    assert sum(f.stat().st_size for f in Path(folder).rglob("*.parquet")) < 2 * wedges


def test_recount_by_lists(spark, repeated):
    g = catalog.literal(spark, [(r.u % 1000, -(r.v % 900), r.t) for r in repeated.edges.collect()])
    w = windows.fixed(spark, [(0, 24), (3, 11), (11, 24), (30, 40)])
    want = sorted(map(tuple, baselines.recount(g, w).collect()))
    assert sorted(map(tuple, baselines.recount_by_lists(g, w).collect())) == want and want[1][-1] > 0
    with pytest.raises(Exception, match="too large"):
        baselines.recount_by_lists(repeated, w).collect()


def test_a_duration_index_leaves_no_wedges_on_disk(spark, folder):
    rnd = random.Random(4)
    g = catalog.literal(spark, [(rnd.randrange(400), rnd.randrange(500), rnd.randrange(1000)) for _ in range(12_000)])
    wedges = baselines.instance_wedges(g, 999).count()
    deltas = spark.createDataFrame([(100,), (300,), (999,)], "delta long")
    written = lambda: sum(f.stat().st_size for f in Path(folder).rglob("*.parquet"))
    for alpha in (0.0, 0.5):
        before = written()
        assert duration.query(duration.build(g, 999, alpha), deltas).count() == 3
        assert written() - before < 2 * wedges, alpha


def test_durations_by_lists(spark, repeated):
    """Repeated edges, spans over one stretch of time and over several, either side, all shares of groups."""
    want = {d: baselines.duration_count(repeated, d).first().butterflies for d in (0, 3, 7, 24)}
    assert want[3] > 10
    for largest, alpha, side in ((3, 0.0, "v"), (7, 0.5, "u"), (24, 0.3, "v"), (24, 1.0, "u"), (1 << 40, 0.0, "v")):
        asked = [d for d in want if d <= largest]
        got = duration.query(duration.build(repeated, largest, alpha, side), spark.createDataFrame([(d,) for d in asked], "delta long"))
        assert {r.delta: r.butterflies for r in got.collect()} == {d: want[d] for d in asked}, (largest, alpha, side)


def test_durations_of_large_groups(spark, small):
    """Groups of thousands of wedges in a stretch are asked by look-ups."""
    g = catalog.load(spark, small, "g9")
    assert max(int(s.size.max()) for r in lists.build(g).collect() for s in lists.stretches(r.data, 719)) > duration.PAIRED
    want = {d: baselines.duration_count(g, d).first().butterflies for d in (24, 200)}
    for largest in (200, 719):
        got = duration.query(duration.build(g, largest, 0.2), spark.createDataFrame([(d,) for d in want], "delta long"))
        assert {r.delta: r.butterflies for r in got.collect()} == want and want[24] > 1000


def test_stretches_are_shared_by_turns_and_worked_off_in_passes(spark, monkeypatch, repeated):
    packed = [r.data for r in lists.build(repeated).collect()]

    def wedges(largest, turns):
        found = [s for data in packed for turn in range(turns) for s in lists.stretches(data, largest, turn=turn, turns=turns)]
        assert all(len(s.group) == s.size.sum() and s.own.any() for s in found)
        return sorted(row for s in found for row in zip(s.size[s.group].tolist(), s.y.tolist(), s.l.tolist(), s.r.tolist(), s.own.tolist(), strict=True))

    for largest in (3, 24):
        monkeypatch.setattr(lists, "WEDGES", 1_500_000)
        whole = wedges(largest, 1)
        monkeypatch.setattr(lists, "WEDGES", 30)
        assert len(whole) > 500 and wedges(largest, 1) == wedges(largest, 3) == whole


def test_a_large_group_is_paired_by_its_starts_and_ends(spark):
    rng, users = np.random.default_rng(5), 60_000
    t = rng.integers(0, 300, (users, 2, 2))
    rows = pa.table({"u": np.repeat(np.arange(users), 4), "v": np.tile([7, 7, 8, 8], users), "t": t.ravel()})
    began = time.monotonic()
    points = lists.enumerated(lists.build(graph.TemporalBipartite(spark.createDataFrame(rows)))).toArrow()
    assert time.monotonic() - began < 60  # some 200,000 points; pairs one by one are 2e10
    l, r, w = (points.column(c).to_numpy() for c in "lrw")  # noqa: E741
    for start, end in ((0, 299), (0, 99), (120, 130), (250, 299)):
        both = int(((t >= start) & (t <= end)).any(axis=2).all(axis=1).sum())
        assert w[(l >= start) & (r <= end)].sum() == both * (both - 1) // 2


@pytest.mark.parametrize("cells", [1, 60, 1 << 20])
def test_pairs_by_cells_are_the_pairs_one_by_one(monkeypatch, cells):
    rng = np.random.default_rng(cells)
    group = np.repeat([0, 1, 2], [400, 5, 150])
    start = rng.integers(0, 40, len(group))
    block = lists.Block(None, None, None, group, start, start + rng.integers(0, 40, len(group)), rng.choice([1, 1, 1, -1], len(group)), np.arange(80))
    monkeypatch.setattr(lists, "CELLS", cells)

    def total():
        found = Counter()
        for columns in lists.paired(block):
            for l, r, w in zip(*(c.tolist() for c in columns), strict=True):  # noqa: E741
                found[l, r] += w
        return {k: w for k, w in found.items() if w}

    by_cells = total()
    monkeypatch.setattr(lists, "MATES", len(group))
    assert by_cells == total()
