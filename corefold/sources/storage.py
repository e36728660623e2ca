"""Chunks, raw blocks and models on disk."""

from __future__ import annotations

import json
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corefold.functions.tensor import Chunks, TensorSpec, index_columns
from corefold.operators import block_kernels as bk
from corefold.operators.decompose import TuckerModel


def write_chunks(chunks: Chunks, path: str, mode: str = "error") -> None:
    """Parquet, sorted by block within each file so that row groups can be skipped."""
    spec = chunks.spec
    keys = index_columns(spec.order, "b")
    chunks.df.sortWithinPartitions(*reversed(keys)).write.mode(mode).option("compression", "zstd").parquet(f"{path}/blocks")
    _write_json(chunks.df.sparkSession, f"{path}/spec", {"dims": spec.dims, "block": spec.block}, mode)


def read_chunks(spark: SparkSession, path: str) -> Chunks:
    spec = _read_json(spark, f"{path}/spec")
    return Chunks(spark.read.parquet(f"{path}/blocks"), TensorSpec(tuple(spec["dims"]), tuple(spec["block"])))


def slice_chunks(chunks: Chunks, mode: int, low: int, high: int) -> Chunks:
    """Blocks that hold an index of low..high: a predicate on block numbers, which the scan takes over."""
    b = chunks.spec.block[mode]
    return Chunks(chunks.df.filter(F.col(f"b_{mode + 1}").between(low // b, high // b)), chunks.spec)


def _write_json(spark: SparkSession, path: str, value: dict, mode: str) -> None:
    spark.createDataFrame([(json.dumps(value),)], "value string").coalesce(1).write.mode(mode).text(path)


def _read_json(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(path).first().value)


def read_raw_blocks(spark: SparkSession, path: str, spec: TensorSpec, pattern: str = r"([0-9_]+)\.f64$") -> Chunks:
    """Files of little-endian float64, one block each, named by block numbers: 0_1_2.f64."""
    n = spec.order
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.f64").load(path)
    numbers = F.split(F.regexp_extract("path", pattern, 1), "_")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                at = tuple(int(x) for x in batch.column(0)[row].as_py())
                yield bk._row(at, np.frombuffer(batch.column(1)[row].as_buffer(), "<f8").reshape(spec.extent(at), order="F"))

    return Chunks(files.select(numbers.alias("at"), "content").mapInArrow(run, bk.chunk_schema(n)), spec)


def factor_frame(spark: SparkSession, model: TuckerModel) -> DataFrame:
    rows = [(m + 1, int(i), int(r), float(u[i, r])) for m, u in enumerate(model.factors) for i in range(u.shape[0]) for r in range(u.shape[1])]
    return spark.createDataFrame(rows, "mode int, i int, r int, u double")


def save_model(model: TuckerModel, path: str, mode: str = "error") -> None:
    """core/, factors/, spectrum/ and meta/ below path."""
    spark = model.core.df.sparkSession
    write_chunks(model.core, f"{path}/core", mode)
    factor_frame(spark, model).coalesce(1).write.mode(mode).parquet(f"{path}/factors")
    rows = [(m + 1, i + 1, float(v)) for m, s in model.spectra.items() for i, v in enumerate(s)]
    spark.createDataFrame(rows, "mode int, pos int, lambda double").coalesce(1).write.mode(mode).parquet(f"{path}/spectrum")
    meta = {"dims": model.dims, "ranks": model.ranks, "norm_sq": model.norm_sq, "core_norm_sq": model.core_norm_sq, "discarded": model.discarded}
    _write_json(spark, f"{path}/meta", meta, mode)


def saved_bytes(spark: SparkSession, model: TuckerModel) -> int:
    """What a saved model takes on disk; it is written below the checkpoint folder and removed again."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="corefold-checkpoint-"))
    place = sc._jvm.org.apache.hadoop.fs.Path(f"{sc._jsc.sc().getCheckpointDir().get()}/{uuid.uuid4().hex}")
    save_model(model, str(place.toString()))
    fs = place.getFileSystem(sc._jsc.hadoopConfiguration())
    size = int(fs.getContentSummary(place).getLength())
    fs.delete(place, True)
    return size


def load_model(spark: SparkSession, path: str) -> TuckerModel:
    meta = _read_json(spark, f"{path}/meta")
    factors = [np.zeros((d, r)) for d, r in zip(meta["dims"], meta["ranks"], strict=True)]
    for row in spark.read.parquet(f"{path}/factors").collect():  # one row for each factor entry
        factors[row.mode - 1][row.i, row.r] = row.u
    spectra: dict[int, list] = {}
    for row in spark.read.parquet(f"{path}/spectrum").orderBy("mode", "pos").collect():
        spectra.setdefault(row.mode - 1, []).append(row["lambda"])
    return TuckerModel(read_chunks(spark, f"{path}/core"), factors, tuple(meta["dims"]), meta["norm_sq"], meta["core_norm_sq"], {m: np.array(s) for m, s in spectra.items()}, {int(k): v for k, v in meta["discarded"].items()})
