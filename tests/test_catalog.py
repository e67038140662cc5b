"""Every query with SQL against DuckDB on the smallest tables."""

import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from hgpart.plans import catalog

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{SF}/{f}'")
    return con


def plain(v):
    if pd.isna(v):
        return "None"
    return f"{float(v):.6g}" if not isinstance(v, (bool, str)) and hasattr(v, "__float__") else str(v)


#: Whole runs take a dozen jobs each; here one of a kind.
SOME_RUNS = {"z_speed_det_w7", "z_quality_flows_w7", "z09_objective_soed_w7", "b_kway_strong_w7", "b_rb_matching_soed_w7"}


@pytest.mark.parametrize("name", sorted(set(catalog.SQL) - catalog.WHOLE | SOME_RUNS))
def test_query_agrees_with_sql(spark, db, name):
    got = catalog.QUERIES[name](spark, SF)
    want = db.sql(catalog.SQL[name])
    assert sorted(got.columns) == sorted(want.columns)
    columns = sorted(want.columns)
    a = sorted(tuple(plain(v) for v in r) for r in got.select(*columns).toPandas().astype(object).itertuples(index=False))
    b = sorted(tuple(plain(v) for v in r) for r in want.df()[columns].astype(object).itertuples(index=False))
    assert a == b


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    blocks = entry.entry(spark)
    assert blocks.columns == ["node", "block"] and blocks.count() > 0
