"""Queries whose sizes and values come from given tables: other rows, other results, and the tables are read by Spark's tasks."""

import glob
import os

import duckdb
import numpy as np
import pandas as pd
import pytest

from corefold import experiments, queries  # noqa: F401  experiments adds its queries
from corefold.sources import arrays

VALUES = ["cost_collectives", "cost_eig", "cost_gram", "cost_hooi", "cost_hooi_exact", "cost_sthosvd", "cost_ttm", "e10_extreme_compression", "e12_layout", "e13_grid_figures"]
FEWER = {"lineitem": "l_orderkey % 3 > 0 AND month(l_shipdate) < 6", "orders": "month(o_orderdate) < 8", "events": "hour(ts) < 9", "part": "p_size % 3 > 0"}


@pytest.fixture(scope="module")
def fewer(sf, tmp_path_factory):
    """The tables without some labels."""
    folder = str(tmp_path_factory.mktemp("fewer"))
    for name, rows in FEWER.items():
        duckdb.sql(f"COPY (SELECT * FROM '{sf}/{name}.parquet' WHERE {rows}) TO '{folder}/{name}.parquet'")
    return folder


def by_sql(folder, name):
    con = duckdb.connect()
    for path in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return ordered(con.execute(queries.SQL[name]).df())


def ordered(df):
    return df.sort_values(list(df.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", VALUES)
def test_results_come_from_the_tables(spark, sf, fewer, name):
    got = ordered(queries.QUERIES[name](spark, fewer).toPandas())
    pd.testing.assert_frame_equal(got, by_sql(fewer, name), check_dtype=False, check_exact=True)
    assert not got.equals(ordered(queries.QUERIES[name](spark, sf).toPandas()))


def test_empty_tables_have_no_costs(spark, sf, tmp_path):
    for name in FEWER:
        duckdb.sql(f"COPY (SELECT * FROM '{sf}/{name}.parquet' LIMIT 0) TO '{tmp_path}/{name}.parquet'")
    assert queries.QUERIES["cost_gram"](spark, str(tmp_path)).count() == 0 == len(by_sql(str(tmp_path), "cost_gram"))


@pytest.mark.parametrize("k", [1, 2])
def test_margins_by_group_have_their_rank(spark, sf, fewer, k):
    """The arrays of e7_weak_scaling and e7_seconds."""
    factors, other = (arrays.ranked_factors(spark, folder, 20 * k, 2 * k) for folder in (sf, fewer))
    assert all(np.linalg.matrix_rank(u) == 2 * k for u in factors)
    assert not np.allclose(factors[0], other[0])
