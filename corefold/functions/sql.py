"""Functions for SQL: `register(spark)` makes them known to a session.

    tucker_words(dims, ranks), tucker_ratio(dims, ranks)   numbers stored, and compression ratio (SQL functions)
    unfold_column(index, dims, mode)                       column of a cell in the unfolding of a mode (from 1)
    block_grids(p, n)                                      every way to write p as n factors (table function)
    norm_rms(x, y)                                         relative error of y (aggregate)
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

_LONGS = "ARRAY<BIGINT>"
#: name -> (parameters, result, body)
SQL_FUNCTIONS = {
    "tucker_words": (f"dims {_LONGS}, ranks {_LONGS}", "BIGINT", "aggregate(ranks, 1L, (a, x) -> a * x) + aggregate(zip_with(dims, ranks, (d, r) -> d * r), 0L, (a, x) -> a + x)"),
    "tucker_ratio": (f"dims {_LONGS}, ranks {_LONGS}", "DOUBLE", "aggregate(dims, 1.0D, (a, x) -> a * x) / tucker_words(dims, ranks)"),
    "unfold_column": (f"index {_LONGS}, dims {_LONGS}, mode INT", "BIGINT", "aggregate(zip_with(index, dims, (i, d) -> struct(i AS i, d AS d)), struct(0L AS at, 1L AS step, 1 AS m), (a, x) -> struct(a.at + IF(a.m = mode, 0L, a.step * x.i) AS at, a.step * IF(a.m = mode, 1L, x.d) AS step, a.m + 1 AS m), a -> a.at)"),
}


@udtf(returnType="grid array<int>")
class BlockGrids:
    def eval(self, p: int, n: int) -> Iterator[tuple[list[int]]]:
        from corefold.plans.planner import enumerate_grids

        for grid in enumerate_grids(p, n):
            yield (list(grid),)


@pandas_udf("double")
def norm_rms(x: pd.Series, y: pd.Series) -> float:
    """Aggregate over a group that fits one task; `functions.measures` has the same without that limit."""
    total = float((x * x).sum())
    return float((((x - y) ** 2).sum() / total) ** 0.5) if total else 0.0


def register(spark: SparkSession) -> None:
    for name, (parameters, result, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {result} RETURN {body}")
    spark.udtf.register("block_grids", BlockGrids)
    spark.udf.register("norm_rms", norm_rms)
