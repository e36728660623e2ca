"""What the decompositions are compared with."""

from __future__ import annotations

import numpy as np
from pyspark.ml.feature import PCA
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.functions import spectrum as sp
from corefold.functions.tensor import Cells
from corefold.operators import block_kernels as bk
from corefold.operators import sql_kernels as sk
from corefold.operators.decompose import materialize


def pca(cells: DataFrame, width: int, rank: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Two-way principal components of rows (row, pos, val): variances, falling, and directions.

    The covariance is summed from pairs within a row: one shuffle by row, then width squared sums.
    """
    sums = cells.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("pos", F.col("val").cast("double").alias("val")))).alias("x"))
    values = sums.select(F.transform("x", lambda p: p["val"]).alias("x"))

    def run(batches):  # noqa: ANN001, ANN202
        s = np.zeros((width + 1, width + 1))  # one column of ones more: its products are the sums and the count
        for batch in batches:
            a = batch.column(0).flatten().to_numpy().reshape(-1, width)
            a = np.hstack([a, np.ones((len(a), 1))])
            s += a.T @ a
        yield from bk._bands(s, 0)

    s = bk._sum_bands(values.mapInArrow(run, "mode int, band int, payload binary"), {0: width + 1})[0]
    n, mean = s[-1, -1], s[-1, :-1] / s[-1, -1]
    cov = s[:-1, :-1] / n - np.outer(mean, mean)
    found, vectors = np.linalg.eigh(cov)
    k = rank or width
    return np.maximum(found[::-1], 0)[:k], vectors[:, ::-1][:, :k]


def library_pca(vectors: DataFrame, column: str, rank: int) -> np.ndarray:
    """Shares of variance by the library's own component."""
    model = PCA(k=rank, inputCol="x", outputCol="y").fit(vectors.select(array_to_vector(F.col(column).cast("array<double>")).alias("x")))
    return model.explainedVariance.toArray()


def relational_st_hosvd(cells: Cells, ranks: tuple[int, ...] | None = None, eps: float | None = None, order: tuple[int, ...] | None = None) -> tuple[Cells, list[np.ndarray], float]:
    """The sequential decomposition with joins and sums of rows alone: core, factors, relative error.

    An independent check of the block kernels, for small arrays: a mode's Gram matrix (which
    goes to the driver, so no mode may be longer than GRAM_LIMIT) pairs all cells of a fibre.
    """
    spec = cells.spec
    if ranks is None and eps is None:
        raise ValueError("give ranks or eps")
    if max(spec.dims) > bk.GRAM_LIMIT:
        raise ValueError(f"no mode may be longer than {bk.GRAM_LIMIT}")
    total = sk.norm_sq(cells).first().norm_sq or 0.0
    budget = (eps or 0.0) ** 2 * total / spec.order
    factors: list[np.ndarray] = [np.zeros((0, 0))] * spec.order
    now = cells
    for mode in range(spec.order) if order is None else order:
        s = np.zeros((spec.dims[mode],) * 2)
        for r in sk.gram(now, mode).toLocalIterator():
            s[r.i, r.j] = r.s
        factors[mode], _ = sp.leading_eigenvectors(s, ranks[mode] if ranks is not None else None, budget)
        rows = sk.factor_rows(cells.df.sparkSession, factors[mode].T)
        now = materialize(sk.ttm(now, rows, mode, factors[mode].shape[1]))
    left = max(total - (sk.norm_sq(now).first().norm_sq or 0.0), 0.0)
    return now, factors, float(np.sqrt(left / total)) if total else 0.0
