"""Every query with SQL against DuckDB on the smallest tables; the others must run."""

import os

import duckdb
import pandas as pd
import pytest
from adaptivejoin import registry


@pytest.fixture(scope="module")
def con(sf_dir):
    c = duckdb.connect()
    for f in os.listdir(sf_dir):
        c.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{sf_dir}/{f}'")
    return c


def plain(v):
    if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and v != v):
        return None
    if isinstance(v, (int, float)) or type(v).__name__ in ("Decimal", "int64", "int32", "float64", "bool_"):
        return str(float(v))
    return str(v)


def rows(df: pd.DataFrame):
    cols = sorted(df.columns)
    return cols, sorted((tuple(map(str, map(plain, r))) for r in zip(*(df[c].astype(object) for c in cols), strict=True)))


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_query(spark, sf_dir, con, name):
    got = registry.QUERIES[name](spark, sf_dir).toPandas()
    if name not in registry.ORACLES:
        assert len(got.columns) > 0
        return
    want = con.sql(registry.ORACLES[name]).df()
    assert rows(got) == rows(want)
