"""Every query with a SQL twin against DuckDB on the smallest tables; known numbers of the blueprint on the next size."""

import glob
import os

import duckdb
import pandas as pd
import pytest

from clipflow.catalog import ORACLES, QUERIES


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    for f in glob.glob(f"{small}/*.parquet"):
        c.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return c


def rows(df, columns):
    def plain(v):
        if isinstance(v, str):
            return v
        if pd.isna(v):
            return None
        return bool(v) if "bool" in type(v).__name__ else float(v)

    return sorted(str(tuple(plain(v) for v in r)) for r in df[columns].astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, small, duck, name):
    got, want = QUERIES[name](spark, small).toPandas(), duck.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got, sorted(got.columns)) == rows(want, sorted(want.columns))


def test_funnel_numbers(spark):
    got = [r.n_clips for r in QUERIES["p_funnel"](spark, "/root/testdata/sf0.01").orderBy("rule_no").collect()]
    assert got == [883, 420, 285, 164, 45, 23]  # with yaw and pitch; by yaw alone 144 and 76 are left


def test_entry_points(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 6
    assert set(e.oracle_sql()) <= set(e.queries())
