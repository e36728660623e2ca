"""Standardising per slice of one mode, before and after."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.functions.tensor import Cells, Chunks
from corefold.operators import block_kernels as bk

#: Fixed value: deviations below this are not divided by.
MIN_SIGMA = 1e-10


def slice_stats(cells: Cells, mode: int, min_sigma: float = MIN_SIGMA) -> DataFrame:
    """var, n, mu, sigma (of the population), scaled; over the cells that are there."""
    stats = cells.df.groupBy(F.col(f"i_{mode + 1}").alias("var")).agg(F.count("*").alias("n"), F.avg("v").alias("mu"), F.stddev_pop("v").alias("sigma"))
    return stats.withColumn("scaled", F.col("sigma") >= min_sigma)


def standardize(cells: Cells, mode: int, min_sigma: float = MIN_SIGMA) -> tuple[Cells, DataFrame]:
    """Mean 0 and deviation 1 in each slice; a constant slice is only centred. Cells must be filled."""
    stats = slice_stats(cells, mode, min_sigma)
    name = f"i_{mode + 1}"
    joined = cells.df.join(stats.withColumnRenamed("var", name), name)
    value = (F.col("v") - F.col("mu")) / F.when(F.col("scaled"), F.col("sigma")).otherwise(1.0)
    return Cells(joined.select(*[c for c in cells.df.columns if c != "v"], value.alias("v")), cells.spec), stats


def unstandardize(cells: Cells, stats: DataFrame, mode: int) -> Cells:
    name = f"i_{mode + 1}"
    joined = cells.df.join(stats.withColumnRenamed("var", name), name)
    value = F.col("v") * F.when(F.col("scaled"), F.col("sigma")).otherwise(1.0) + F.col("mu")
    return Cells(joined.select(*[c for c in cells.df.columns if c != "v"], value.alias("v")), cells.spec)


def gram_standardized(chunks: Chunks, mode: int, variable: int, min_sigma: float = MIN_SIGMA) -> np.ndarray:
    """Gram matrix of the standardised array from one scan of the raw one.

    One Gram matrix and row sums for each variable, then mean and deviation are applied
    to these. Loses digits where a mean is large against its deviation, so it refuses
    when more than about ten digits would go. Both modes must be unsplit.
    """
    spec, n = chunks.spec, chunks.spec.order
    if mode == variable or spec.grid[mode] > 1 or spec.grid[variable] > 1:
        raise ValueError("needs two different unsplit modes")
    length, count = spec.dims[mode], spec.dims[variable]
    each = spec.size // length // count

    def run(batches):  # noqa: ANN001, ANN202
        # one row of ones more: its products are the row sums
        s = np.zeros((count, length + 1, length + 1))
        for batch in batches:
            for _, array in bk.read_blocks(batch, n):
                moved = np.moveaxis(array, (variable, mode), (0, 1)).reshape(count, length, -1)
                more = np.concatenate([moved, np.ones((count, 1, moved.shape[2]))], axis=1)
                s += more @ more.transpose(0, 2, 1)
        for v in range(count):
            yield from bk._bands(s[v], v)

    found = bk._sum_bands(chunks.df.mapInArrow(run, "mode int, band int, payload binary"), {v: length + 1 for v in range(count)})
    s, rows = np.stack([found[v][:-1, :-1] for v in range(count)]), np.stack([found[v][-1, :-1] for v in range(count)])
    mu = rows.sum(axis=1) / (each * length)
    square = np.einsum("vii->v", s) / (each * length)
    sigma = np.sqrt(np.maximum(square - mu**2, 0.0))
    if np.any((sigma > 0) & (square > 1e10 * sigma**2)):
        raise ValueError("means are too large against deviations: standardise first")
    scale = np.where(sigma >= min_sigma, sigma, 1.0)
    out = np.zeros((length, length))
    for v in range(count):
        centred = s[v] - mu[v] * (rows[v][:, None] + rows[v][None, :]) + each * mu[v] ** 2
        out += centred / scale[v] ** 2
    return out
