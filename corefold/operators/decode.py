"""All or part of the array from a model."""

from __future__ import annotations

from collections.abc import Iterator
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.functions.tensor import Cells, Chunks, TensorSpec, index_columns, indices
from corefold.operators import block_kernels as bk
from corefold.operators.decompose import TuckerModel

#: A core of at most so many values is sent to every task; a larger one is multiplied where it lies.
CORE_VALUES = 32 << 20


def restrict(model: TuckerModel, select: dict[int, object] | None = None, weights: dict[int, np.ndarray] | None = None) -> tuple[list[np.ndarray], list[list[int]]]:
    """Factor rows that a selection needs, and their indices; weights (rows x length) pool rows instead."""
    rows, labels = [], []
    for mode, u in enumerate(model.factors):
        if weights and mode in weights:
            rows.append(np.asarray(weights[mode], dtype=float) @ u)
            labels.append(list(range(len(weights[mode]))))
        else:
            wanted = indices((select or {}).get(mode, slice(None)), len(u))
            rows.append(u[wanted])
            labels.append(wanted)
    return rows, labels


def plan_expansion(ranks: tuple[int, ...], sizes: tuple[int, ...]) -> list[int]:
    """Modes in the order that keeps intermediate arrays smallest: least growth first."""
    return sorted(range(len(ranks)), key=lambda m: sizes[m] / ranks[m])


def reconstruct(model: TuckerModel, select: dict[int, object] | None = None, weights: dict[int, np.ndarray] | None = None, block: tuple[int, ...] | None = None) -> Chunks:
    """The selected sub-array; factor rows are cut before anything is multiplied."""
    rows, _ = restrict(model, select, weights)
    sizes = tuple(len(r) for r in rows)
    order = plan_expansion(model.ranks, sizes)
    if prod(model.ranks) > CORE_VALUES:
        return bk.ttm_chain(model.core, dict(enumerate(rows)), order=order)
    spec = TensorSpec(sizes, block or tuple(min(s, 64) for s in sizes))
    spark = model.core.df.sparkSession
    shared = spark.sparkContext.broadcast((bk.to_array(model.core, CORE_VALUES), rows))
    n = spec.order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        core, own = shared.value
        for batch in batches:
            for number in batch.column(0).to_pylist():
                at = tuple(int(i) for i in np.unravel_index(number, spec.grid))
                out = core
                for m in order:
                    out = bk.times(np.asfortranarray(out), own[m][at[m] * spec.block[m] : (at[m] + 1) * spec.block[m]], m)
                yield bk._row(at, out)

    return Chunks(spark.range(prod(spec.grid)).mapInArrow(run, bk.chunk_schema(n)), spec)


def reconstruct_cells(model: TuckerModel, select: dict[int, object] | None = None, weights: dict[int, np.ndarray] | None = None) -> Cells:
    """Like reconstruct, as rows under the original indices."""
    _, labels = restrict(model, select, weights)
    made = bk.to_cells(reconstruct(model, select, weights))
    names = index_columns(len(model.dims))
    df = made.df
    for name, own in zip(names, labels, strict=True):
        if own != list(range(len(own))):
            df = df.withColumn(name, F.element_at(F.array(*[F.lit(i) for i in own]), F.col(name) + 1))
    return Cells(df, TensorSpec(model.dims))


def decode_cells(model: TuckerModel, places: DataFrame) -> DataFrame:
    """v for each row of i_1 .. i_N; rank-many products a row. Other columns are kept out."""
    names = index_columns(len(model.dims))
    spark = places.sparkSession
    shared = spark.sparkContext.broadcast((bk.to_array(model.core, CORE_VALUES), model.factors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        core, factors = shared.value
        for whole in batches:
            for at in range(0, whole.num_rows, 4096):
                batch = whole.slice(at, 4096)
                out = np.broadcast_to(core, (batch.num_rows, *core.shape))
                for m in range(len(factors) - 1, -1, -1):
                    u = factors[m][batch.column(m).to_numpy()]
                    out = np.einsum("b...r,br->b...", out, u)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], names=[*names, "v"])

    return places.select(*[F.col(n).cast("int").alias(n) for n in names]).mapInArrow(run, ", ".join(f"{n} int" for n in names) + ", v double")
