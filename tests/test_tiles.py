"""Numbers of groups by size from tiles, against wedges as rows, and what they leave on disk."""

import random
import uuid
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from bflyspark.operators import indexes, lists
from bflyspark.operators.wedges import group_sizes, priority_wedges
from bflyspark.sources import catalog, graph, scratch


def test_words_without_locality_are_stored_once(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(scratch, "scratch", lambda spark, label: f"{tmp_path}/{label}-{uuid.uuid4().hex}")
    monkeypatch.setattr(lists, "PART", 2000)
    rng, docs, words = np.random.default_rng(1), 2000, 100
    names = rng.integers(-(1 << 62), 1 << 62, 20_000)
    u, v = np.repeat(np.arange(docs), words), names[(20_000 * rng.random(docs * words) ** 4).astype(int)]
    g = graph.TemporalBipartite(spark.createDataFrame(pa.table({"u": u, "v": v, "t": u})))
    sizes = sorted(map(tuple, indexes.wedge_sizes(g).collect()))
    assert sum(f.stat().st_size for f in Path(tmp_path).rglob("*.parquet")) < 20 * len(u)
    monkeypatch.undo()
    assert sizes == sorted(map(tuple, lists.histogram(lists.build(g)).collect()))


@pytest.mark.parametrize("least, wedges, dense", [(200_000, 2_000_000, 4), (50, 30, 4), (50, 30, 0), (50, 100, 1000)])
def test_tiles_hold_all_groups(spark, monkeypatch, least, wedges, dense):
    tiles = pytest.importorskip("bflyspark.operators.tiles")
    for name, value in (("LEAST", least), ("WEDGES", wedges), ("DENSE", dense)):
        monkeypatch.setattr(tiles, name, value)
    rnd = random.Random(2)
    name = lambda k: (-1) ** k * (1 << 62) + k if k % 3 == 0 else k
    g = catalog.literal(spark, [(name(int(40 * rnd.random() ** 2)), name(int(30 * rnd.random() ** 2)), rnd.randrange(25)) for _ in range(500)])
    want = group_sizes(priority_wedges(g)).groupBy("size").agg(F.count("*"))
    assert sorted(map(tuple, tiles.histogram(g).collect())) == sorted(map(tuple, want.collect()))


def test_no_edges_have_no_groups(spark):
    assert indexes.wedge_sizes(graph.TemporalBipartite(spark.createDataFrame([], "u long, v long, t long"))).count() == 0
