"""Sizes, index arithmetic and blocks of dense N-way arrays.

Modes are numbered from 0 here; indices start at 0; the first mode varies fastest.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce
from itertools import product
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TensorSpec:
    """Sizes of an array and of its blocks (by default one block)."""

    dims: tuple[int, ...]
    block: tuple[int, ...] = ()

    def __post_init__(self) -> None:
        if not self.dims or min(self.dims) < 1:
            raise ValueError("every mode needs at least one index")
        block = self.block or self.dims
        if len(block) != len(self.dims) or min(block) < 1:
            raise ValueError("one block length for each mode")
        object.__setattr__(self, "block", tuple(min(b, d) for b, d in zip(block, self.dims, strict=True)))

    @property
    def order(self) -> int:
        return len(self.dims)

    @property
    def size(self) -> int:
        return prod(self.dims)

    def co_size(self, mode: int) -> int:
        """Length of a row of the unfolding."""
        return self.size // self.dims[mode]

    @property
    def grid(self) -> tuple[int, ...]:
        """Blocks along each mode; edge blocks may be shorter."""
        return tuple(-(-d // b) for d, b in zip(self.dims, self.block, strict=True))

    def extent(self, at: tuple[int, ...]) -> tuple[int, ...]:
        return tuple(min(b, d - i * b) for i, b, d in zip(at, self.block, self.dims, strict=True))

    def resized(self, mode: int, length: int, block: int | None = None) -> TensorSpec:
        dims, blocks = list(self.dims), list(self.block)
        dims[mode], blocks[mode] = length, block or min(self.block[mode], length)
        return replace(self, dims=tuple(dims), block=tuple(blocks))

    def on_grid(self, grid: tuple[int, ...]) -> TensorSpec:
        return replace(self, block=tuple(-(-d // g) for d, g in zip(self.dims, grid, strict=True)))


def index_columns(n: int, prefix: str = "i") -> list[str]:
    return [f"{prefix}_{k + 1}" for k in range(n)]


@dataclass(frozen=True)
class Cells:
    """An array as rows: i_1 .. i_N int, v (double, or long for exact work). Cells that lack are zero."""

    df: DataFrame
    spec: TensorSpec


@dataclass(frozen=True)
class Chunks:
    """An array as blocks: b_1 .. b_N int, extent array<int>, payload (float64, little-endian, first mode fastest)."""

    df: DataFrame
    spec: TensorSpec
    labels: dict = field(default_factory=dict, compare=False)


def unfold_weights(dims: tuple[int, ...], mode: int) -> list[int]:
    """What each index adds to the column: the product of the sizes before it, without the unfolded mode."""
    weights, running = [], 1
    for k, d in enumerate(dims):
        weights.append(0 if k == mode else running)
        if k != mode:
            running *= d
    return weights


def unfold_index(spec: TensorSpec, mode: int) -> tuple[Column, Column]:
    """(row, column) of a cell in the unfolding; arithmetic only, so nothing moves."""
    names = index_columns(spec.order)
    terms = [F.col(n).cast("long") * w for n, w in zip(names, unfold_weights(spec.dims, mode), strict=True) if w]
    return F.col(names[mode]), reduce(lambda a, b: a + b, terms, F.lit(0).cast("long"))


def fold_index(spec: TensorSpec, mode: int, row: str = "row", col: str = "col") -> list[Column]:
    """The index columns of a cell from its place in the unfolding."""
    out, running = [], 1
    for k, (name, d) in enumerate(zip(index_columns(spec.order), spec.dims, strict=True)):
        if k == mode:
            out.append(F.col(row).cast("int").alias(name))
        else:
            out.append(F.pmod(F.floor(F.col(col) / running), F.lit(d)).cast("int").alias(name))
            running *= d
    return out


def offset(spec: TensorSpec) -> Column:
    """Place of a cell in storage."""
    names, terms, running = index_columns(spec.order), [], 1
    for n, d in zip(names, spec.dims, strict=True):
        terms.append(F.col(n).cast("long") * running)
        running *= d
    return reduce(lambda a, b: a + b, terms)


def blocks(spec: TensorSpec) -> list[tuple[int, ...]]:
    return list(product(*(range(g) for g in spec.grid)))


def slice_cells(cells: Cells, select: dict[int, object]) -> DataFrame:
    """Rows within a selection: mode -> int, list, range or slice."""
    df = cells.df
    for mode, chosen in select.items():
        column = F.col(f"i_{mode + 1}")
        wanted = indices(chosen, cells.spec.dims[mode])
        if len(wanted) > 1 and wanted == list(range(wanted[0], wanted[-1] + 1)):
            df = df.filter(column.between(wanted[0], wanted[-1]))
        elif len(wanted) > 2 and len({b - a for a, b in zip(wanted, wanted[1:], strict=False)}) == 1:
            step = wanted[1] - wanted[0]
            df = df.filter(column.between(wanted[0], wanted[-1]) & (F.pmod(column - wanted[0], F.lit(step)) == 0))
        else:
            df = df.filter(column.isin(wanted))
    return df


def indices(chosen: object, length: int) -> list[int]:
    """A selector as indices in rising order."""
    if isinstance(chosen, int):
        chosen = [chosen]
    if isinstance(chosen, slice):
        chosen = range(*chosen.indices(length))
    found = sorted(set(int(i) for i in chosen))
    if not found or found[0] < 0 or found[-1] >= length:
        raise IndexError(f"selection outside 0..{length - 1}")
    return found
