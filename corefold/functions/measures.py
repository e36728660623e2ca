"""Accuracy, size and compression."""

from __future__ import annotations

from math import prod, sqrt

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corefold.functions.tensor import Cells, index_columns


def error_measures(x: Cells, y: Cells) -> DataFrame:
    """One row: norm_rms and max_abs of x - y; a cell that one side lacks is zero there."""
    names = index_columns(x.spec.order)
    both = x.df.select(*names, F.col("v").alias("x")).join(y.df.select(*names, F.col("v").alias("y")), names, "full")
    a, b = F.coalesce("x", F.lit(0.0)), F.coalesce("y", F.lit(0.0))
    return both.agg(F.sqrt(F.sum((a - b) * (a - b)) / F.sum(a * a)).alias("norm_rms"), F.max(F.abs(a - b)).alias("max_abs"))


def storage_words(dims: tuple[int, ...], ranks: tuple[int, ...]) -> int:
    return prod(ranks) + sum(i * r for i, r in zip(dims, ranks, strict=True))


def compression_ratio(dims: tuple[int, ...], ranks: tuple[int, ...]) -> float:
    return prod(dims) / storage_words(dims, ranks)


def saved_fraction(dims: tuple[int, ...], ranks: tuple[int, ...]) -> float:
    return 1 - 1 / compression_ratio(dims, ranks)


def bytes_of(dims: tuple[int, ...], word: int = 8) -> int:
    return prod(dims) * word


def spectrum_frame(spark: SparkSession, spectra: dict[int, np.ndarray]) -> DataFrame:
    """mode, pos (from 1), lambda: as many rows as the modes are long together."""
    rows = [(int(m) + 1, int(i) + 1, float(v)) for m, s in spectra.items() for i, v in enumerate(s)]
    return spark.createDataFrame(rows, "mode int, pos int, lambda double")


def mode_error_curve(spectrum: DataFrame, norm_sq: float | None = None) -> DataFrame:
    """For each mode and rank the energy that the rank leaves out, absolute and relative to the norm."""
    after = Window.partitionBy("mode").orderBy(F.desc("pos")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("mode")
    tail = F.coalesce(F.sum("lambda").over(after), F.lit(0.0))
    total = F.lit(norm_sq) if norm_sq is not None else F.sum("lambda").over(whole)
    return spectrum.withColumn("tail_sq", tail).withColumn("rel_tail", F.sqrt(F.col("tail_sq") / total))


def rank_at(curve: DataFrame, eps: float, modes: int) -> DataFrame:
    """Least rank of each mode whose curve is at or under the threshold line."""
    return curve.filter(F.col("rel_tail") <= eps / sqrt(modes)).groupBy("mode").agg(F.min("pos").alias("rank"))


def thosvd_bound(spectra: dict[int, np.ndarray], ranks: tuple[int, ...], norm_sq: float) -> float:
    """Relative error that truncating every mode to these ranks cannot exceed."""
    return sqrt(sum(float(spectra[m][r:].sum()) for m, r in enumerate(ranks)) / norm_sq) if norm_sq else 0.0


def check_energy(model) -> float:  # noqa: ANN001
    """Relative gap between discarded energy and the difference of norms."""
    return abs(sum(model.discarded.values()) - model.residual_sq) / model.norm_sq if model.norm_sq else 0.0


def fit_trace(model) -> list[float]:  # noqa: ANN001
    return [s.fit_sq for s in model.trace if s.kernel == "fit"]
