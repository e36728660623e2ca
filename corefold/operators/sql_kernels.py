"""The same kernels on rows, for small arrays and exact whole-number work: all in built-in functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corefold.functions.tensor import Cells, index_columns


def norm_sq(cells: Cells) -> DataFrame:
    return cells.df.agg(F.sum(F.col("v") * F.col("v")).alias("norm_sq"))


def gram(cells: Cells, mode: int, symmetric: bool = False) -> DataFrame:
    """i, j, s: cells that share all other indices meet, then sums by pair."""
    names = index_columns(cells.spec.order)
    others = [n for k, n in enumerate(names) if k != mode]
    own = names[mode]
    a = cells.df.withColumnRenamed(own, "i").withColumnRenamed("v", "x")
    b = cells.df.withColumnRenamed(own, "j").withColumnRenamed("v", "y")
    pairs = a.join(b, others) if others else a.crossJoin(b)  # one mode: a vector of at most its length
    if symmetric:
        pairs = pairs.filter("i <= j")
    return pairs.groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("s"))


def factor_rows(spark: SparkSession, matrix: np.ndarray, exact: bool = False) -> DataFrame:
    """r, i, u of a matrix K x length. Its size is that of one mode's factor."""
    kind, cast = ("long", int) if exact else ("double", float)
    rows = [(int(r), int(i), cast(matrix[r, i])) for r in range(matrix.shape[0]) for i in range(matrix.shape[1])]
    return spark.createDataFrame(rows, f"r int, i int, u {kind}")


def ttm(cells: Cells, factor: DataFrame, mode: int, length: int) -> Cells:
    """factor: r, i, u rows of a K x length matrix."""
    names = index_columns(cells.spec.order)
    others = [n for k, n in enumerate(names) if k != mode]
    joined = cells.df.withColumnRenamed(names[mode], "i").join(factor, "i")  # Spark broadcasts it below its own size check
    out = joined.groupBy(*others, F.col("r").alias(names[mode])).agg(F.sum(F.col("v") * F.col("u")).alias("v"))
    return Cells(out.select(*names, "v"), cells.spec.resized(mode, length))
