"""SQL of the training-data queries against their rows."""

import duckdb
import pandas as pd
import pytest

from hgpart.llm.queries import COMPANIONS, ORACLE_SQL, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_sql_agrees(spark, sf, name):
    db = duckdb.connect()
    for t in ("documents", "pages", "benchmark"):
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want, got = db.sql(ORACLE_SQL[name]).df(), (QUERIES | COMPANIONS)[name](spark, sf).toPandas()
    key = want.columns[0]
    want, got = want.sort_values(key).reset_index(drop=True), got[list(want.columns)].sort_values(key).reset_index(drop=True)
    pd.testing.assert_frame_equal(got.astype(object).where(got.notna(), None), want.astype(object).where(want.notna(), None), check_dtype=False)
