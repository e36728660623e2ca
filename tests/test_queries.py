"""Every query runs; those with SQL agree with DuckDB."""

import glob
import os

import duckdb
import pandas as pd
import pytest

from corefold import experiments, queries

#: Timings of what other queries check.
SLOW = {"e4_grid_seconds", "e5_order_seconds", "e6_seconds", "e7_seconds"}


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for path in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def ordered(df):
    df = df[sorted(df.columns)]
    return df.sort_values(list(df.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_agrees_with_sql(spark, sf, duck, name):
    got = ordered(queries.QUERIES[name](spark, sf).toPandas())
    want = ordered(duck.execute(queries.SQL[name]).df())
    pd.testing.assert_frame_equal(got, want, check_dtype=False, check_exact=True)


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.SQL) - SLOW))
def test_runs(spark, sf, name):
    assert queries.QUERIES[name](spark, sf).count() > 0


def test_experiment_module_registers():
    assert set(experiments.CASES) == {"strong", "grid", "order", "weak"} and len(queries.QUERIES) > 130
