"""`spark.read.format('corefold')`: cells of a stored model, decoded as they are read.

Options: path (a folder of save_model, local or any store that pyarrow reads), parts (by
default one for each CELLS_A_PART cells). Filters on i_1 .. i_N (=, <, <=, >, >=, in) are
taken over: only the factor rows they leave are multiplied. A part is decoded box by box,
at most CELLS_AT_ONCE cells at a time.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from math import prod

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs as pafs
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from corefold.functions.tensor import index_columns
from corefold.operators.block_kernels import times

CELLS_A_PART, CELLS_AT_ONCE = 1 << 24, 1 << 19


def _store(path: str) -> tuple[pafs.FileSystem, str]:
    """The file system of a path or URI, and the path within."""
    if path.startswith("file:"):
        path = "/" + path.removeprefix("file:").lstrip("/")
    return pafs.FileSystem.from_uri(path) if "://" in path else (pafs.LocalFileSystem(), path)


def _json(store: tuple[pafs.FileSystem, str], folder: str) -> dict:
    files, root = store
    part = next(f.path for f in files.get_file_info(pafs.FileSelector(f"{root}/{folder}")) if f.base_name.startswith("part-"))
    with files.open_input_stream(part) as f:
        return json.loads(f.read())


def _table(store: tuple[pafs.FileSystem, str], folder: str) -> pa.Table:
    return pq.read_table(f"{store[1]}/{folder}", filesystem=store[0])


def _boxes(wanted: list[list[int]], most: int) -> Iterator[list[list[int]]]:
    """The wanted indices of each mode in boxes of at most `most` cells; the last modes are cut first."""
    inner = 1
    for mode, own in enumerate(wanted):
        if inner * len(own) > most:
            size = max(1, most // inner)
            for at in range(0, len(own), size):
                for rest in _boxes(wanted[mode + 1 :], 1):
                    yield [*wanted[:mode], own[at : at + size], *rest]
            return
        inner *= len(own)
    yield list(wanted)


class CorefoldDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "corefold"

    def schema(self) -> str:
        n = len(_json(_store(self.options["path"]), "meta")["dims"])
        return ", ".join(f"{c} int" for c in index_columns(n)) + ", v double"

    def reader(self, schema: StructType) -> CorefoldReader:
        return CorefoldReader(self.options["path"], int(self.options.get("parts", 0)))


class CorefoldReader(DataSourceReader):
    def __init__(self, path: str, parts: int):
        self.path, self.parts = path, parts
        self.dims = tuple(_json(_store(path), "meta")["dims"])
        self.wanted = [list(range(d)) for d in self.dims]

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802  the interface's name
        tests = {EqualTo: lambda i, v: i == v, LessThan: lambda i, v: i < v, LessThanOrEqual: lambda i, v: i <= v, GreaterThan: lambda i, v: i > v, GreaterThanOrEqual: lambda i, v: i >= v, In: lambda i, v: i in v}
        names = index_columns(len(self.dims))
        for f in filters:
            test = tests.get(type(f))
            if test is None or f.attribute[0] not in names:
                yield f
                continue
            mode = names.index(f.attribute[0])
            self.wanted[mode] = [i for i in self.wanted[mode] if test(i, f.value)]

    def partitions(self) -> list[InputPartition]:
        """Along the last mode."""
        last = self.wanted[-1]
        parts = self.parts or -(-prod(map(len, self.wanted)) // CELLS_A_PART)
        size = max(1, -(-len(last) // max(parts, 1)))
        return [InputPartition(last[at : at + size]) for at in range(0, max(len(last), 1), size)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        wanted = [*self.wanted[:-1], partition.value]
        if not all(wanted):
            return
        store = _store(self.path)
        meta, spec = _json(store, "meta"), _json(store, "core/spec")
        factors = [np.zeros((d, r)) for d, r in zip(meta["dims"], meta["ranks"], strict=True)]
        table = _table(store, "factors").to_pydict()
        for m, i, r, u in zip(table["mode"], table["i"], table["r"], table["u"], strict=True):
            factors[m - 1][i, r] = u
        core = np.zeros(meta["ranks"])
        blocks = _table(store, "core/blocks")
        n = len(self.dims)
        for row in range(blocks.num_rows):
            at = [blocks.column(k)[row].as_py() for k in range(n)]
            extent = blocks.column("extent")[row].as_py()
            where = tuple(slice(a * b, a * b + e) for a, b, e in zip(at, spec["block"], extent, strict=True))
            core[where] = np.frombuffer(blocks.column("payload")[row].as_buffer(), "<f8").reshape(extent, order="F")
        for box in _boxes(wanted, CELLS_AT_ONCE):
            out = core
            for m in reversed(range(n)):  # the modes that a box has least of come first
                out = times(np.asfortranarray(out), factors[m][box[m]], m)
            grid = np.unravel_index(np.arange(out.size), out.shape, order="F")
            columns = [pa.array(np.array(w, dtype=np.int32)[g]) for w, g in zip(box, grid, strict=True)]
            whole = pa.RecordBatch.from_arrays([*columns, pa.array(out.ravel(order="F"))], names=[*index_columns(n), "v"])
            for at in range(0, whole.num_rows, 1 << 16):
                yield whole.slice(at, 1 << 16)


def register(spark) -> None:  # noqa: ANN001
    """Make the format known; taking over filters is a runtime setting that is off by default."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(CorefoldDataSource)
