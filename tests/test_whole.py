"""Queries that stand for a whole job and not for its first rows."""

import pytest
from pyspark.sql import functions as F

from bflyspark.operators import hardness
from bflyspark.plans import graph_queries, relops
from bflyspark.sources import catalog


def test_the_full_list_is_as_long_as_the_count(spark, small):
    run = graph_queries.registry()
    count = run["duration_direct_g2"][0](spark, small).first()["butterflies"]
    rows = run["duration_list_all_g2"][0](spark, small)
    assert rows.count() == count > 100


def test_bitmaps_and_structs_of_all_edges(spark):
    run, sf = relops.registry(), "/root/testdata/sf0.01"
    edges = [(r.u, r.v) for r in catalog.load(spark, sf, "g4").edges.collect()]
    partners = {}
    for u, v in edges:
        partners.setdefault(v, set()).add(u)
    assert max(u for u, _ in edges) >= 64
    assert {r.v: r.n for r in run["rel_a13_bitmaps_all"][0](spark, sf).collect()} == {v: len(us) for v, us in partners.items()}
    assert sorted((r.a, r.b) for r in run["rel_f8_structs_all"][0](spark, sf).collect()) == sorted(edges + [(v, u) for u, v in edges])


def test_five_thousand_random_windows(spark, small):
    run = graph_queries.registry()
    got = {r.window_id: r for r in run["random_windows_5000_g2"][0](spark, small).collect()}
    assert sorted(got) == list(range(5000))
    assert all(got[r.window_id] == r for r in run["random_windows_hybrid_g2"][0](spark, small).collect())


@pytest.mark.parametrize("exact", [False, True])
def test_right_degrees_follow_their_bound_and_the_left_sum(spark, exact):
    law = (3000, 400, 2.5, 2.5, 200, 40)
    left, right = hardness.expected_degrees(spark, *law, seed=3)
    g = hardness.power_law(spark, *law, seed=3, exact=exact)
    row = hardness.balance(g, left, right).first()
    assert row.expected_u == pytest.approx(row.expected_v) and right.agg(F.max("dv")).first()[0] <= 40
    assert row.max_v <= 40 + 5 * 40**0.5 and row.sum_v == pytest.approx(row.expected_v, rel=0.1)
    with pytest.raises(ValueError):
        hardness.expected_degrees(spark, 3000, 10, 2.5, 2.5, 200, 40)


@pytest.mark.parametrize("name", ["duplicate_edges_windows", "toy_windows", "power_law_double", "power_law_exact", "power_law_single", "uniform_times", "rel_s7_ranges", "rel_s8_literal", "rel_v6_tree_nodes"])
def test_queries_read_a_given_table(spark, small, monkeypatch, name):
    read, table = [], catalog.table
    monkeypatch.setattr(catalog, "table", lambda s, d, n: read.append(n) or table(s, d, n))
    assert ({**graph_queries.registry(), **relops.registry()})[name][0](spark, small).count()
    assert read
