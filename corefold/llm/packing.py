"""Best-fit packing planned over the histogram of lengths (operator 7) and token counts (operator 6).

Documents become pieces of at most `limit` tokens; how many pieces there are of each
length decides how they are packed, so the plan is made from at most `limit` counts
on the driver, and its size does not depend on the number of documents. Each piece
then takes the slot that the plan has for its rank among the pieces of its length.
Ranks are found by (length, salt), so a length that a third of the pieces share is
dealt out over many tasks.

Null texts are empty (a piece of one end-of-text id); a null doc_id stays null;
repeated rows are packed once each; no rows give no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corefold.llm import bpe
from corefold.llm.common import give_back, map_columns, slices, text_or_empty, written

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Bins(NamedTuple):
    """`count` sequences of one make-up: (length, how many of it) in the order they stand."""

    pattern: tuple[tuple[int, int], ...]
    count: int


def plan_best_fit(counts: dict[int, int], limit: int) -> list[Bins]:
    """Best fit, longest first, over counts: bins of one make-up are filled together.

    A step splits one group of bins in at most two, so there are at most about
    three groups for each length.
    """
    free: list[list[Bins]] = [[] for _ in range(limit + 1)]  # by room left
    for length in sorted(counts, reverse=True):
        left = counts[length]
        if not 0 < length <= limit:
            raise ValueError(f"length {length} is not within 1..{limit}")
        room = length
        while left and room <= limit:
            if not free[room]:
                room += 1
                continue
            pattern, count = free[room].pop()
            each = room // length
            filled = min(count, left // each)
            if filled:
                free[room - each * length].append(Bins((*pattern, (length, each)), filled))
                left -= filled * each
                count -= filled
            if count and left and left < each:
                free[room - left * length].append(Bins((*pattern, (length, left)), 1))
                left, count = 0, count - 1
            if count:
                free[room].append(Bins(pattern, count))
        if left:
            each = limit // length
            if left // each:
                free[limit - each * length].append(Bins(((length, each),), left // each))
            if left % each:
                free[limit - left % each * length].append(Bins(((length, left % each),), 1))
    return [b for group in free for b in group]


class Slots:
    """Where the r-th piece of each length goes, from a plan."""

    def __init__(self, plan: list[Bins]):
        rows: dict[int, list[tuple[int, int, int, int]]] = {}
        base = 0
        for pattern, count in plan:
            at = 0
            for length, each in pattern:
                rows.setdefault(length, []).append((each * count, base, each, at))
                at += length * each
            base += count
        self.sequences = base
        self.by_length = {}
        for length, found in rows.items():
            size, first, each, at = (np.array(x, dtype=np.int64) for x in zip(*found, strict=True))
            self.by_length[length] = (np.cumsum(size) - size, first, each, at)

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sequence, offset = np.empty(len(rank), dtype=np.int64), np.empty(len(rank), dtype=np.int64)
        for value in np.unique(length):
            rows = np.flatnonzero(length == value)
            begin, first, each, at = self.by_length[int(value)]
            group = np.searchsorted(begin, rank[rows], side="right") - 1
            within = rank[rows] - begin[group]
            sequence[rows] = first[group] + within // each[group]
            offset[rows] = at[group] + within % each[group] * value
        return sequence, offset


def cut(total: int, limit: int) -> list[tuple[int, int]]:
    """(start, length) of each piece: all of `limit` but the first, which may be shorter."""
    first = total % limit or limit
    return [(0, min(first, total)), *((at, limit) for at in range(first, total, limit))]


def pieces(docs: DataFrame, path: str, limit: int, end_id: int) -> DataFrame:
    """Every document's pieces, with the CRC-32 of each one's ids."""
    end = np.array([end_id], dtype="<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(path)
        for whole in batches:
            for batch in slices(whole, "text", 4 << 20):
                rows: list[tuple] = []
                for doc_id, packed in zip(batch.column(0).to_pylist(), enc.encode_all(batch.column(1).to_pylist()), strict=True):
                    ids = packed + end
                    rows += [(doc_id, i, start, size, zlib.crc32(ids[4 * start : 4 * (start + size)])) for i, (start, size) in enumerate(cut(len(ids) // 4, limit))]
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])
        give_back()

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(run, PIECES)


def pack(docs: DataFrame, path: str, limit: int = 1024, end_id: int = 2) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    cut_up = written(pieces(docs, path, limit, end_id))
    salts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    salted = cut_up.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)))
    sizes = written(salted.groupBy("length", "salt").agg(F.count("*").alias("n")))
    counts = {r.length: r.n for r in sizes.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `limit` rows
    slots = spark.sparkContext.broadcast(Slots(plan_best_fit(counts, limit)))  # bounded by `limit`
    before = sizes.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    order = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "start", "ids_crc32")
    ranked = salted.join(before.hint("merge"), ["length", "salt"]).withColumn("rank", F.col("before") + F.row_number().over(order) - 1)

    def place(batch: pa.RecordBatch) -> pa.RecordBatch:
        length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
        sequence, offset = slots.value.place(length, rank)
        return pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], names=[*batch.schema.names[:5], "sequence_id", "offset"])

    chosen = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank")
    return map_columns(chosen, place, PIECES + ", sequence_id long, offset long", rows=100_000)


def token_lengths(docs: DataFrame, path: str) -> DataFrame:
    """doc_id and the number of tokens of each whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = bpe.encoder(path)
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                sizes = [len(ids) // 4 for ids in enc.encode_all(part.column(1).to_pylist())]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64())], names=["doc_id", "n_tokens"])
        give_back()

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(run, "doc_id long, n_tokens long")


def length_histogram(lengths: DataFrame) -> DataFrame:
    """Exact histogram of n_tokens and its running sums.

    For each length that occurs: n_docs; docs_longer and tokens_longer (suffix sums:
    documents longer than it, and their tokens); docs_total, tokens_total; quantile
    (share of documents not longer); truncated_total (tokens left if every document
    were cut to this length). The rows are distinct lengths, not documents: running
    sums are made within blocks of 128 lengths and then carried over the blocks.
    """
    block = 128
    # written: a few thousand rows that stand for the whole corpus, which is tokenized once
    counts = written(lengths.groupBy("n_tokens").agg(F.count("*").alias("n_docs")))
    counts = counts.withColumn("block", F.floor(F.col("n_tokens") / block))
    tokens = F.col("n_tokens") * F.col("n_docs")
    inner = Window.partitionBy("block").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, -1)
    outer = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    blocks = counts.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum(tokens).alias("t"))
    blocks = blocks.select("block", F.coalesce(F.sum("d").over(outer), F.lit(0)).alias("d_after"), F.coalesce(F.sum("t").over(outer), F.lit(0)).alias("t_after"), F.sum("d").over(everything).alias("docs_total"), F.sum("t").over(everything).alias("tokens_total"))
    out = counts.withColumn("d_in", F.coalesce(F.sum("n_docs").over(inner), F.lit(0))).withColumn("t_in", F.coalesce(F.sum(tokens).over(inner), F.lit(0))).join(blocks, "block")
    longer = F.col("d_after") + F.col("d_in")
    tokens_longer = F.col("t_after") + F.col("t_in")
    return out.select(
        "n_tokens",
        "n_docs",
        longer.alias("docs_longer"),
        tokens_longer.alias("tokens_longer"),
        "docs_total",
        "tokens_total",
        ((F.col("docs_total") - longer) / F.col("docs_total")).alias("quantile"),
        (F.col("tokens_total") - tokens_longer + longer * F.col("n_tokens")).alias("truncated_total"),
    )


def at_limit(histogram: DataFrame, limit: int) -> DataFrame:
    """Totals at any context limit, whether a document has that length or not: one row."""
    cut_short = F.least(F.col("n_tokens"), F.lit(limit))
    return histogram.agg(F.sum("n_docs").alias("docs_total"), F.sum(F.when(F.col("n_tokens") > limit, F.col("n_docs")).otherwise(0)).alias("docs_truncated"), F.sum(cut_short * F.col("n_docs")).alias("truncated_total"))
