"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the session names; one of our own only where it names none (tests)."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="corefold-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame) -> DataFrame:
    """Compute once, into the shared checkpoint folder; a lost executor costs nothing then."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, instead_of: Iterable[DataFrame] = ()) -> DataFrame:
    """Like materialize, but as compressed Parquet below the shared checkpoint folder: columnar and prunable.

    `instead_of`: written tables that only df was made from; they are removed once df stands.
    """
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    instead_of = list(instead_of)
    for old in instead_of:
        place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(old._written_at)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    if instead_of:  # the shuffles behind them go once the driver's collector has seen that nobody holds them
        spark.sparkContext._jvm.System.gc()
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path
    return out


def partitions_for(df: DataFrame, bytes_each: int = 16 << 20) -> int:
    """Buckets that keep what one task gathers bounded, however large the input is."""
    spark = df.sparkSession
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(size // bytes_each, 200_000))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def map_columns(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str, rows: int = 2000) -> DataFrame:
    """mapInArrow with batches of at most `rows` rows, so that a Python worker's memory stays bounded."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                out = fn(batch.slice(at, rows))
                if out is not None and out.num_rows:
                    yield out

    return df.mapInArrow(run, schema)


#: What this worker process remembers between tasks (see make_room).
REMEMBERED: list[dict] = []


def make_room() -> None:
    """Forget what tasks of other operators have left in this worker: workers are reused, and their executor's memory is shared."""
    for memory in REMEMBERED:
        memory.clear()
    give_back()


def give_back() -> None:
    """Hand freed memory of this worker back."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def slices(batch: pa.RecordBatch, column: str, most_bytes: int) -> Iterator[pa.RecordBatch]:
    """Runs of rows whose `column` (string or binary) holds at most about `most_bytes`; a longer row comes alone."""
    import numpy as np
    import pyarrow.compute as pc

    sizes = np.nan_to_num(np.asarray(pc.binary_length(batch.column(column)).fill_null(0)), nan=0).astype("int64")
    total = np.cumsum(sizes)
    at = 0
    while at < batch.num_rows:
        before = total[at - 1] if at else 0
        end = int(np.searchsorted(total, before + most_bytes, side="right"))
        end = max(at + 1, end)
        yield batch.slice(at, end - at)
        at = end
