"""Every registered query with DuckDB text, side by side on the smallest tables."""

import duckdb
import pandas as pd
import pytest

from bflyspark.plans import graph_queries, relops
from bflyspark.plans.sqlapi import TABLES

REGISTRY = {**graph_queries.registry(), **relops.registry()}
SLOW = {"sampled_error_g1", "enumerated_grid_g2", "hybrid_g1_a01", "hybrid_g1_a10", "hybrid_g2_a01", "hybrid_g2_a10"}


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for name in TABLES:
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{small}/{name}.parquet'")
    return con


def cell(v):
    if v is None or v is pd.NA or v != v:
        return "null"
    if isinstance(v, float):
        return str(int(v)) if v == int(v) else str(round(v, 6))
    return str(v)


def rows(df):
    df = df.reindex(sorted(df.columns), axis=1)
    return sorted((tuple(map(cell, r)) for r in df.astype(object).values.tolist()), key=str)


@pytest.mark.parametrize("name", sorted(set(REGISTRY) - SLOW))
def test_against_duckdb(spark, duck, small, name):
    run, sql = REGISTRY[name]
    got = run(spark, small).toPandas()
    if sql is None:
        assert len(got.columns)
        return
    want = duck.sql(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)
