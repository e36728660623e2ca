"""Exact substring removal by external suffix sorting (operator 2).

Every byte is removed that lies in a string of `w` bytes which also starts earlier (in
a document of smaller doc_id, or before in the same one). Anchors (see `windows`) first
tell which strings can have a partner at all: runs of strings that stand elsewhere as a
whole, and runs that share an anchor with different ones. The latter are cut out and
dealt into shards by anchor, so equal strings share a shard, and each shard's text is
suffix-sorted with common prefixes (see `suffix`); neighbours that share `w` bytes are
one class of strings, of which all but the earliest are repeats.

An anchor with very many different surroundings would make a hot shard: its strings
are dealt out one by one instead, each by its own bytes.

A null text is empty. Rows without doc_id are earlier than no other and stay whole. Rows
that share a doc_id count as one document: of equal offsets none is the earlier.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.llm import suffix, windows
from corefold.llm.anchors import mix, scheme
from corefold.llm.common import give_back, partitions_for, slices, text_or_empty, written

RUN = np.dtype([("doc", "<i8"), ("tid", "<i8"), ("first", "<i4"), ("size", "<i4")])
#: Bytes of tuples that a shard's queue holds before it uses the disk.
QUEUE_MEMORY = 32 << 20


def cut_out(docs: DataFrame, found: DataFrame, spec: windows.Spec, parts: int) -> DataFrame:
    """The open runs' texts, by shard: doc, tid, first string's start, length, bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text", windows.SLICE):
                texts = [t.encode() for t in batch.column(2).to_pylist()]
                doc, tid, first, size, key, data = [], [], [], [], [], []
                for i, blob in enumerate(batch.column(3).to_pylist()):
                    runs = np.frombuffer(blob, dtype=windows.OPEN)
                    a, n, h = runs["first"].astype(np.int64), runs["n"].astype(np.int64) + 1, runs["h"]
                    if runs["hot"].any():
                        a, n, h = _apart(np.frombuffer(texts[i], dtype=np.uint8), a, n, h, runs["hot"] == 1, spec.w)
                    text = texts[i]
                    data += [text[x : x + y] for x, y in zip(a.tolist(), (n + spec.w - 1).tolist(), strict=True)]
                    first.append(a)
                    size.append(n + spec.w - 1)
                    key.append(h)
                    doc.append(np.full(len(a), batch.column(0)[i].as_py(), dtype=np.int64))
                    tid.append(np.full(len(a), batch.column(1)[i].as_py(), dtype=np.int64))
                shard = mix(np.concatenate(key)) % np.uint64(parts)
                yield from _by_shard(shard, np.concatenate(doc), np.concatenate(tid), np.concatenate(first).astype(np.int32), np.concatenate(size).astype(np.int32), np.array(data, dtype=object))
        give_back()

    return windows.map_joined(docs, found.filter(F.length("open") > 0).select("doc_id", "tid", "open"), run, windows.PACKED, "inner")


def _by_shard(shard: np.ndarray, doc: np.ndarray, tid: np.ndarray, first: np.ndarray, size: np.ndarray, data: np.ndarray) -> Iterator[pa.RecordBatch]:
    """One row for each shard: its runs' records and texts, compressed."""
    import zstandard

    order = np.argsort(shard, kind="stable")
    shard = shard[order]
    cut = np.concatenate([[0], np.flatnonzero(shard[1:] != shard[:-1]) + 1, [len(shard)]])
    runs, data = windows.records(RUN, doc, tid, first, size)[order], data[order]
    press = zstandard.ZstdCompressor(level=1).compress
    blobs = [press(b"".join([np.int64(b - a).tobytes(), runs[a:b].tobytes(), *data[a:b].tolist()])) for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
    part = pa.array(shard[cut[:-1]].astype(np.int32))
    yield pa.RecordBatch.from_arrays([part, pa.array([windows.PIECES] * len(blobs), pa.int32()), pa.array(blobs, pa.binary())], names=["part", "kind", "blob"])


def _of_shard(table: pa.Table) -> tuple[np.ndarray, list[bytes]]:
    """The runs of a shard, and their texts."""
    import zstandard

    runs, data = [], []
    for blob in table.column("blob"):
        raw = zstandard.ZstdDecompressor().decompress(blob.as_buffer())
        at = 8 + int(np.frombuffer(raw, "<i8", 1)[0]) * RUN.itemsize
        own = np.frombuffer(raw[8:at], dtype=RUN)
        runs.append(own)
        for size in own["size"].tolist():
            data.append(raw[at : at + size])
            at += size
    return np.concatenate(runs), data


def _apart(text: np.ndarray, first: np.ndarray, n: np.ndarray, h: np.ndarray, hot: np.ndarray, w: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hot runs cut into single strings, each dealt out by its own hash."""
    own = scheme(0)
    prefix = own.prefix(own.bytes[text])
    a, m = first[hot], n[hot]
    within = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
    starts = np.repeat(a, m) + within
    keys = mix(own.spans(prefix, starts, starts + w))
    cold = ~hot
    return np.concatenate([first[cold], starts]), np.concatenate([n[cold], np.ones(len(starts), dtype=np.int64)]), np.concatenate([h[cold], keys])


def sort_shards(packed: DataFrame, spec: windows.Spec, parts: int, memory: int = QUEUE_MEMORY) -> DataFrame:
    """Repeats by document, found by sorting each shard's suffixes."""

    def run(table: pa.Table) -> pa.Table:
        runs, data = _of_shard(table)
        size = runs["size"]
        places, groups = _equal_strings(data, spec.w, memory)
        end = np.cumsum(size.astype(np.int64) + 1)
        run_of = np.searchsorted(end, places, side="right")
        at = places - (end[run_of] - size[run_of] - 1)
        fits = at + spec.w <= size[run_of]
        run_of, at, groups = run_of[fits], at[fits], groups[fits]
        start = (runs["first"][run_of] + at).astype(np.int32)
        d, t = runs["doc"][run_of], runs["tid"][run_of]
        c = windows.classes((groups,), d, start, spec.by_doc)
        out = list(windows.send_repeats(parts, c, d, t, start, np.zeros(len(start), dtype=np.int32)))
        give_back()
        return windows.sent(out)

    return packed.groupBy("part").applyInArrow(run, windows.PACKED)


def _equal_strings(data: list[bytes], w: int, memory: int) -> tuple[np.ndarray, np.ndarray]:
    """(places, class) of the suffixes whose first w bytes another suffix has too; each text ends with one 0 more."""
    text = np.frombuffer(b"\xff".join([*data, b""]), dtype=np.uint8) + np.uint8(1)  # UTF-8 has no byte 255
    order, common = suffix.sorted_suffixes(text, w, memory)
    same = common >= w
    member = same.copy()
    member[:-1] |= same[1:]
    group = np.cumsum(~same)
    return order[member].astype(np.int64), group[member]


def remove_repeats(docs: DataFrame, w: int = 100, k: int = 32, **limits: int) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept (the bytes that are left), of every row."""
    found = repeats(docs, w, k, **limits)
    everything = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).withColumn("tid", F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text", 4 << 20):
                rows: list[list] = [[], [], [], [], []]
                for text, blobs in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                    data = text.encode()
                    kept, spans = remove_spans(data, blobs, w)
                    for column, value in zip(rows, (len(data), len(data) - len(kept), spans, hashlib.sha256(kept).hexdigest(), kept), strict=True):
                        column.append(value)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(rows, kinds, strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return windows.map_joined(everything, found, run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary", "left")


def clean_texts(docs: DataFrame, w: int = 100, k: int = 32) -> DataFrame:
    """docs with text (and n_chars, if there) of what is left; a character of which any byte goes, goes."""
    found = repeats(docs, w, k).select(F.col("doc_id").alias("doc"), F.col("tid").alias("doc_tid"), "spans")
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("own"), F.xxhash64(text_or_empty()).alias("own_tid"))
    joined = rows.join(found, (F.col("own") == F.col("doc")) & (F.col("own_tid") == F.col("doc_tid")), "left").select("row.*", F.col("spans"))
    joined = joined.toDF(*[f"c{i}" for i in range(len(docs.columns))], "spans")  # by place, whatever they are called
    at = docs.columns.index("text")
    count = docs.columns.index("n_chars") if "n_chars" in docs.columns else None
    schema = joined.drop("spans").schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, whole.schema.names[at], 4 << 20):
                texts = [t if t is None or not b else remove_spans(t.encode(), b, w)[0].decode("utf-8", "ignore") for t, b in zip(batch.column(at).to_pylist(), batch.column(batch.num_columns - 1).to_pylist(), strict=True)]
                columns = list(batch.columns[:-1])
                columns[at] = pa.array(texts, batch.schema.field(at).type)
                if count is not None:
                    columns[count] = pa.array([None if t is None else len(t) for t in texts], batch.schema.field(count).type)
                yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names[:-1])

    return joined.mapInArrow(run, schema).toDF(*docs.columns)


def remove_spans(data: bytes, blobs: list[bytes] | None, w: int) -> tuple[bytes, int]:
    """What is left of a document, and how many maximal runs went."""
    if not blobs:
        return data, 0
    spans = np.frombuffer(b"".join(blobs), dtype=windows.SPAN)
    a, b = windows.covered(spans["start"], spans["end"], w)
    kept, at = [], 0
    for x, y in zip(a.tolist(), b.tolist(), strict=True):
        kept.append(data[at:x])
        at = y
    kept.append(data[at:])
    return b"".join(kept), len(a)


def repeats(docs: DataFrame, w: int = 100, k: int = 32, **limits: int) -> DataFrame:
    """doc_id, tid, spans (packed) of the documents that repeat a string of w bytes. limits: hot, heavy, flush (see windows.Spec)."""
    spec = windows.Spec(w, k, words=False, by_doc=False, **limits)
    parts = partitions_for(docs, 3 << 20)
    known = windows.identified(docs)
    found = windows.repeated(known, spec, parts)
    sorted_ = windows.by_document(sort_shards(cut_out(known, found, spec, parts), spec, parts))
    both = found.select("doc_id", "tid", "spans").unionByName(sorted_.select("doc_id", "tid", "spans")).filter(F.length("spans") > 0)
    return written(both.groupBy("doc_id", "tid").agg(F.collect_list("spans").alias("spans")), instead_of=[found])  # two at most
