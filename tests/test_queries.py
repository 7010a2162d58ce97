"""Every query of the graph engine against its SQL on the smallest tables."""

import glob
import os

import duckdb
import pandas as pd
import pytest

from propgraph import workload_queries

DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in glob.glob(f"{DIR}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    return c


def plain(v):
    if pd.isna(v):
        return None
    return v if isinstance(v, (str, bool)) else str(pd.Timestamp(v)) if hasattr(v, "year") else round(float(v), 5)


def rows(df):
    cols = sorted(df.columns)
    return sorted((tuple(map(plain, r)) for r in df[cols].itertuples(index=False, name=None)), key=repr)


@pytest.mark.parametrize("name", sorted(workload_queries.ORACLES))
def test_same_as_sql(spark, con, name):
    got = workload_queries.QUERIES[name](spark, DIR).toPandas()
    want = con.execute(workload_queries.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", sorted(set(workload_queries.QUERIES) - set(workload_queries.ORACLES)))
def test_runs(spark, name):
    assert workload_queries.QUERIES[name](spark, DIR).count() > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 20
    assert set(e.oracle_sql()) <= set(e.queries())
