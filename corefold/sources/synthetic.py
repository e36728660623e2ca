"""Arrays of known make-up."""

from __future__ import annotations

from collections.abc import Iterator
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession

from corefold.functions.tensor import Chunks, TensorSpec
from corefold.operators import block_kernels as bk


def known_factors(dims: tuple[int, ...], ranks: tuple[int, ...], seed: int = 0, decay: float = 0.0) -> tuple[np.ndarray, list[np.ndarray]]:
    """A core (entries fall by 10**-decay with each index step) and orthonormal factors."""
    rng = np.random.default_rng(seed)
    core = rng.standard_normal(ranks)
    if decay:
        core *= 10.0 ** (-decay * sum(np.indices(ranks)))
    return core, [np.linalg.qr(rng.standard_normal((d, r)))[0] for d, r in zip(dims, ranks, strict=True)]


def synthetic(spark: SparkSession, dims: tuple[int, ...], ranks: tuple[int, ...], block: tuple[int, ...] | None = None, seed: int = 0, noise: float = 0.0, decay: float = 0.0) -> Chunks:
    """An array of random core and factors."""
    return from_factors(spark, *known_factors(dims, ranks, seed, decay), block, seed, noise)


def from_factors(spark: SparkSession, core: np.ndarray, factors: list[np.ndarray], block: tuple[int, ...] | None = None, seed: int = 0, noise: float = 0.0) -> Chunks:
    """Core times factors, made block by block on the executors; noise is seeded by block."""
    dims = tuple(len(u) for u in factors)
    spec = TensorSpec(dims, block or dims)
    shared = spark.sparkContext.broadcast((core, factors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        core, factors = shared.value
        for batch in batches:
            for number in batch.column(0).to_pylist():
                at = tuple(int(i) for i in np.unravel_index(number, spec.grid))
                out = np.asfortranarray(core)
                for m, u in enumerate(factors):
                    out = np.asfortranarray(bk.times(out, u[at[m] * spec.block[m] : (at[m] + 1) * spec.block[m]], m))
                if noise:
                    out = out + noise * np.random.default_rng((seed, number)).standard_normal(out.shape)
                yield bk._row(at, out)

    blocks = prod(spec.grid)
    return Chunks(spark.range(0, blocks, 1, min(blocks, 4 * spark.sparkContext.defaultParallelism)).mapInArrow(run, bk.chunk_schema(spec.order)), spec)
