"""Every query with oracle SQL, against DuckDB on the smallest tables."""

import glob
import os

import duckdb
import pandas as pd
import pytest

from relstrata.plans import registry


def views(con, sf):
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")


def plain(df: pd.DataFrame) -> list:
    def cell(v):
        if v is None or v is pd.NA or (isinstance(v, float) and v != v):
            return "null"
        if isinstance(v, float):
            return f"{v:.9g}"
        return str(v.item()) if hasattr(v, "item") else str(v)

    df = df[sorted(df.columns)]
    return sorted(tuple(map(cell, row)) for row in df.itertuples(index=False))


def same(a: pd.DataFrame, b: pd.DataFrame) -> bool:
    assert sorted(a.columns) == sorted(b.columns)
    x, y = plain(a), plain(b)
    assert x == y, (list(set(x) - set(y))[:3], list(set(y) - set(x))[:3])
    return True


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(name, spark, sf):
    con = duckdb.connect()
    views(con, sf)
    assert same(registry.queries()[name](spark, sf).toPandas(), con.sql(registry.oracle_sql()[name]).df())
