"""Windows that also stand elsewhere: the stages that operators 2 and 10 share.

1. Every document's anchors (see `anchors`), without what a task can already tell to be a
   repeat, are written down, with a count of them by bucket of their hash (an array of
   fixed size for each task).
2. They are dealt to parts by their hash. Where a bucket holds far more than its share,
   some anchor is very common: its records are dealt by their whole context instead.
3. In a part, equal contexts are one class; all but its earliest place are repeats.
   Earliest places stay open that share an anchor, and what stands before or after it over
   half of a window's other symbols, with a different context: some of their windows may
   stand in it. So do all of a bucket dealt by context.
4. All go back to the documents' buckets, and become one row per document.

Contexts are equal if both of two independent hashes (one of 64 bits, one of 32 and 16 more
for each side of the anchor) and the anchor's own are. Open
contexts are resolved by the operators, each by its own method. Documents are told apart by
doc_id and a hash of their text (`tid`), and ordered by doc_id.

What is sent on are rows (part, kind, records): all of a task's for one part in one row.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corefold.llm import anchors
from corefold.llm.common import give_back, make_room, slices, text_or_empty, written

PACKED = "part int, kind int, blob binary"
FOUND = "doc_id long, tid long, spans binary, open binary"
#: Kinds of records.
BY_ANCHOR, REPEATS, OPENED, BY_CONTEXT, COUNTS, PIECES = range(6)
#: Bytes of text that are hashed at once.
SLICE = 1 << 20
#: Anchors in one row; a row of less than half a megabyte is no burden to the JVM's heap.
ROW = 10_000
#: Buckets of anchors that are counted.
BUCKETS = 1 << 16

ANCHOR = np.dtype([("h", "<u8"), ("ctx", "<u8"), ("alt", "<u8"), ("doc", "<i8"), ("tid", "<i8"), ("first", "<i4"), ("n", "<i2")])
SPAN = np.dtype([("start", "<i4"), ("end", "<i4"), ("src_doc", "<i8"), ("src_tid", "<i8"), ("src_start", "<i4")])
OPEN = np.dtype([("first", "<i4"), ("n", "<i4"), ("h", "<u8"), ("hot", "u1")])
_OWNER = [("doc", "<i8"), ("tid", "<i8")]
REPEAT, OPENING = np.dtype(_OWNER + SPAN.descr), np.dtype(_OWNER + OPEN.descr)


class Spec(NamedTuple):
    w: int  # symbols in a window
    k: int  # symbols in an anchor
    words: bool  # symbols are words, else bytes
    by_doc: bool  # repeats within a document don't count
    seed: int = 0  # which hashes
    bits: int = 64  # of each hash; fewer only to see what happens when different texts meet
    hot: int = 2_000  # contexts of one anchor from which on they are dealt out by what lies around it
    heavy: int = 1_000_000  # records of a bucket beyond its share from which on it is dealt by context
    flush: int = 150_000  # anchors that a task gathers before it sends them on


_WHITE = np.zeros(256, dtype=bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True


def symbols(texts: list[bytes], words: bool, seed: int = 0) -> tuple[tuple[np.ndarray, np.ndarray], np.ndarray]:
    """Two codes for each symbol of the texts laid end to end, and where each text begins."""
    one, two = anchors.scheme(2 * seed), anchors.scheme(2 * seed + 1)
    if not words:
        sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        data = np.frombuffer(b"".join(texts), dtype=np.uint8)
        return (one.bytes[data], two.bytes[data]), np.concatenate([[0], np.cumsum(sizes)])
    data = np.frombuffer(b" ".join([*texts, b""]), dtype=np.uint8)
    sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts)) + 1
    at = np.concatenate([[0], np.cumsum(sizes)])
    if not len(data):
        none = np.zeros(0, dtype=np.uint64)
        return (none, none), np.zeros(len(texts) + 1, dtype=np.int64)
    white = _WHITE[data]
    edge = np.flatnonzero(white[1:] != white[:-1]) + 1
    if not white[0]:
        edge = np.concatenate([[0], edge])
    start, end = edge[0::2], edge[1::2]  # the last byte is white
    size = (end - start).astype(np.uint64)
    codes = tuple(anchors.mix(s.spans(s.prefix(s.bytes[data]), start, end) + size) for s in (one, two))
    return codes, np.searchsorted(start, at)


def identified(docs: DataFrame) -> DataFrame:
    """doc_id, tid, text of the documents that have an id."""
    return docs.filter("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).withColumn("tid", F.xxhash64("text")).select("doc_id", "tid", "text")


def _bucket(doc_id: np.ndarray, parts: int) -> np.ndarray:
    return (anchors.mix(doc_id.astype(np.uint64)) >> np.uint64(8)) % np.uint64(parts)


def records(dtype: np.dtype, *columns: np.ndarray) -> np.ndarray:
    out = np.empty(len(columns[0]), dtype=dtype)
    for name, column in zip(dtype.names, columns, strict=True):
        out[name] = column
    return out


def _rows(part: np.ndarray, kind: int, offsets: np.ndarray, data: bytes) -> pa.RecordBatch:
    blobs = pa.Array.from_buffers(pa.binary(), len(part), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(data)])
    return pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), pa.array(np.full(len(part), kind, dtype=np.int32)), blobs], names=["part", "kind", "blob"])


def by_part(part: np.ndarray, kind: int, found: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Rows (part, kind, records), in the order they stand."""
    if not len(part):
        return
    order = np.argsort(part, kind="stable")
    part = part[order]
    cut = np.concatenate([[0], np.flatnonzero(part[1:] != part[:-1]) + 1, [len(part)]])
    yield _rows(part[cut[:-1]], kind, cut * found.dtype.itemsize, found[order].tobytes())


def gather(table: pa.Table, kind: int, dtype: np.dtype) -> np.ndarray:
    """All records of one kind."""
    return np.frombuffer(b"".join(b.as_py() for k, b in zip(table.column("kind"), table.column("blob"), strict=True) if k.as_py() == kind), dtype=dtype)


def passed_on(table: pa.Table, kind: int) -> list[pa.RecordBatch]:
    import pyarrow.compute as pc

    return table.select(["part", "kind", "blob"]).filter(pc.equal(table.column("kind"), kind)).to_batches()


def sent(batches: list[pa.RecordBatch]) -> pa.Table:
    return pa.Table.from_batches(batches, schema=pa.schema([("part", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())]))


class Classes(NamedTuple):
    """Of records that are equal: order sorts by class and place; lead is each sorted record's class leader."""

    order: np.ndarray
    lead: np.ndarray
    repeat: np.ndarray


def classes(keys: tuple[np.ndarray, ...], doc: np.ndarray, first: np.ndarray, by_doc: bool) -> Classes:
    """Records are equal if all their keys are."""
    order = np.lexsort((first, doc, keys[0]))
    one = keys[0][order]
    new = np.ones(len(one), dtype=bool)
    np.not_equal(one[1:], one[:-1], out=new[1:])
    if any(((k[order][1:] != k[order][:-1]) & ~new[1:]).any() for k in keys[1:]):  # the first key is not enough
        order = np.lexsort((first, doc, *keys[::-1]))
        new[1:] = np.any([k[order][1:] != k[order][:-1] for k in keys], axis=0)
    at = np.maximum.accumulate(np.where(new, np.arange(len(new)), 0))
    lead = order[at]
    later = doc[order] > doc[lead]
    repeat = later if by_doc else later | (first[order] > first[lead])
    return Classes(order, lead, repeat)


def send_repeats(parts: int, c: Classes, doc: np.ndarray, tid: np.ndarray, first: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
    """REPEATS of each record that repeats its leader, by document."""
    rows, lead = c.order[c.repeat], c.lead[c.repeat]
    again = np.lexsort((first[rows], tid[rows], doc[rows]))
    rows, lead = rows[again], lead[again]
    start, end = first[rows], first[rows] + n[rows]
    d, t, sd, st, ss = doc[rows], tid[rows], doc[lead], tid[lead], first[lead]
    if len(rows):  # join what goes on in the same source
        new = np.ones(len(rows), dtype=bool)
        new[1:] = (d[1:] != d[:-1]) | (t[1:] != t[:-1]) | (start[1:] != end[:-1] + 1) | (sd[1:] != sd[:-1]) | (st[1:] != st[:-1]) | (ss[1:] - start[1:] != ss[:-1] - start[:-1])
        at = np.flatnonzero(new)
        end = end[np.concatenate([at[1:], [len(rows)]]) - 1]
        d, t, start, sd, st, ss = (x[at] for x in (d, t, start, sd, st, ss))
    yield from by_part(_bucket(d, parts), REPEATS, records(REPEAT, d, t, start, end, sd, st, ss))


def _classes(x: np.ndarray, spec: Spec) -> Classes:
    return classes((np.ascontiguousarray(x["ctx"]), x["alt"], x["h"]), x["doc"], x["first"], spec.by_doc)


def _bucket_of(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(48)).astype(np.int64)  # BUCKETS = 1 << 16


def anchor_rows(docs: DataFrame, spec: Spec, parts: int) -> DataFrame:
    """Stage 1. REPEATS by document; anchors (BY_ANCHOR) and their COUNTS, not yet dealt to a part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        counts = np.zeros(BUCKETS, dtype=np.int64)
        mask = np.uint64((1 << spec.bits) - 1)
        make_room()

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal counts
            if not held:
                return
            x = np.concatenate(held)
            held.clear()
            c = _classes(x, spec)
            yield from send_repeats(parts, c, x["doc"], x["tid"], x["first"], x["n"].astype(np.int32))
            x = x[np.sort(c.order[~c.repeat])]
            counts += np.bincount(_bucket_of(x["h"]), minlength=BUCKETS)
            for at in range(0, len(x), ROW):
                y = x[at : at + ROW]
                yield _rows(np.array([-1]), BY_ANCHOR, np.array([0, y.nbytes]), y.tobytes())

        for whole in batches:
            for batch in slices(whole, "text", SLICE):
                texts = [t.encode() for t in batch.column(2).to_pylist()]
                codes, begin = symbols(texts, spec.words, spec.seed)
                f = anchors.Anchors(codes, begin, spec.w, spec.k, spec.seed)
                if len(f.first):
                    doc, tid = batch.column(0).to_numpy()[f.doc], batch.column(1).to_numpy()[f.doc]
                    held.append(records(ANCHOR, f.h, f.ctx & mask, f.alt & mask, doc, tid, f.first - begin[f.doc], f.last - f.first))
                del codes, f
                if sum(map(len, held)) >= spec.flush:
                    yield from flush()
        yield from flush()
        if counts.any():
            yield _rows(np.array([-1]), COUNTS, np.array([0, counts.nbytes]), counts.tobytes())
        give_back()

    return docs.mapInArrow(run, PACKED)


def heavy_buckets(rows: DataFrame, spec: Spec) -> np.ndarray:
    """Which buckets of anchors hold far more than their share. At most 64 arrays of fixed size reach the driver."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, dtype=np.int64)
        for batch in batches:
            for blob in batch.column(0):
                total += np.frombuffer(blob.as_buffer(), dtype=np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["blob"])

    sums = rows.filter(F.col("kind") == COUNTS).select("blob").coalesce(64).mapInArrow(add, "blob binary").collect()
    total = sum((np.frombuffer(r.blob, dtype=np.int64) for r in sums), np.zeros(BUCKETS, dtype=np.int64))
    return total > 1.5 * total.mean() + spec.heavy


def dealt(rows: DataFrame, heavy: np.ndarray, parts: int) -> DataFrame:
    """Stage 2. Anchors by their hash, or by context (BY_CONTEXT) where their bucket is heavy; the rest as it is."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held: list[bytes] = []
            for kind, blob in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                if kind == BY_ANCHOR:
                    held.append(blob.as_buffer().to_pybytes())
                if held and sum(map(len, held)) > 6 << 20:
                    yield from _deal(held, heavy, parts)
                    held.clear()
            if held:
                yield from _deal(held, heavy, parts)
        give_back()

    by_anchor = rows.filter(F.col("kind") == BY_ANCHOR).mapInArrow(run, PACKED)
    return by_anchor.unionByName(rows.filter(F.col("kind") == REPEATS))


def _deal(held: list[bytes], heavy: np.ndarray, parts: int) -> Iterator[pa.RecordBatch]:
    x = np.frombuffer(b"".join(held), dtype=ANCHOR)
    crowded = heavy[_bucket_of(x["h"])]
    for kind, key, chosen in ((BY_ANCHOR, "h", ~crowded), (BY_CONTEXT, "ctx", crowded)):
        y = x[chosen] if crowded.any() else x if kind == BY_ANCHOR else x[:0]
        yield from by_part(anchors.mix(y[key]) % np.uint64(parts), kind, y)


def _meeting(x: np.ndarray, leads: np.ndarray, spec: Spec) -> tuple[np.ndarray, np.ndarray]:
    """For each record that leads a class: whether another class of its anchor may share a window with it, and how many of the anchor's do."""
    h = x["h"][leads]
    met = np.zeros(len(leads), dtype=bool)
    for side in anchors.sides(x["alt"][leads]) if spec.bits == 64 else [np.ones(len(leads), dtype=np.uint64)]:
        order = np.lexsort((side, h))
        same = (h[order][1:] == h[order][:-1]) & (side[order][1:] == side[order][:-1]) & (side[order][1:] > 0)
        met[order[1:][same]] = met[order[:-1][same]] = True
    out, size = np.zeros(len(x), dtype=bool), np.zeros(len(x), dtype=np.int64)
    out[leads] = met
    _, group, many = np.unique(h[met], return_inverse=True, return_counts=True)
    size[leads[met]] = many[group]
    return out, size


def resolve_parts(packed: DataFrame, spec: Spec, parts: int) -> DataFrame:
    """Stage 3. REPEATS and OPENED, both by document."""

    def run(table: pa.Table) -> pa.Table:
        out = passed_on(table, REPEATS)
        for kind in (BY_ANCHOR, BY_CONTEXT):
            x = gather(table, kind, ANCHOR)
            if not len(x):
                continue
            c = _classes(x, spec)
            out += send_repeats(parts, c, x["doc"], x["tid"], x["first"], x["n"].astype(np.int32))
            stay = np.sort(c.order[~c.repeat])
            if kind == BY_ANCHOR:
                lead = np.empty(len(x), dtype=np.int64)
                lead[c.order] = c.lead
                met, size = _meeting(x, np.unique(c.lead), spec)
                stay = stay[met[lead[stay]]]
                hot = size[lead[stay]] > spec.hot
            else:
                hot = np.ones(len(stay), dtype=bool)
            y = x[stay]
            out += by_part(_bucket(y["doc"], parts), OPENED, records(OPENING, y["doc"], y["tid"], y["first"], y["n"], y["h"], hot))
        return sent(out)

    return packed.groupBy("part").applyInArrow(run, PACKED)


def by_document(packed: DataFrame) -> DataFrame:
    """Stage 4. doc_id, tid, spans (SPAN records) and open (OPEN records), of the documents that have any."""

    def run(table: pa.Table) -> pa.Table:
        rows: dict[tuple[int, int], list[bytes]] = {}
        for kind, dtype, own, at in ((REPEATS, REPEAT, SPAN, 0), (OPENED, OPENING, OPEN, 1)):
            x = gather(table, kind, dtype)
            if not len(x):
                continue
            x = x[np.lexsort((x[own.names[0]], x["tid"], x["doc"]))]
            doc, tid = x["doc"], x["tid"]
            cut = np.concatenate([[0], np.flatnonzero((doc[1:] != doc[:-1]) | (tid[1:] != tid[:-1])) + 1, [len(doc)]])
            found = records(own, *(x[name] for name in own.names))
            for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                rows.setdefault((int(doc[a]), int(tid[a])), [b"", b""])[at] = found[a:b].tobytes()
        columns = [[k[0] for k in rows], [k[1] for k in rows], [v[0] for v in rows.values()], [v[1] for v in rows.values()]]
        schema = pa.schema([("doc_id", pa.int64()), ("tid", pa.int64()), ("spans", pa.binary()), ("open", pa.binary())])
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    return packed.groupBy("part").applyInArrow(run, FOUND)


def repeated(docs: DataFrame, spec: Spec, parts: int) -> DataFrame:
    """Stages 1 to 4 over identified documents, written down."""
    rows = written(anchor_rows(docs, spec, parts))
    return written(by_document(resolve_parts(dealt(rows, heavy_buckets(rows, spec), parts), spec, parts)), instead_of=[rows])


def map_joined(docs: DataFrame, found: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str, how: str) -> DataFrame:
    """fn over doc_id, tid, text and the columns of `found`, joined on document."""
    rest = [c for c in found.columns if c not in ("doc_id", "tid")]
    return docs.join(found, ["doc_id", "tid"], how).select("doc_id", "tid", "text", *rest).mapInArrow(fn, schema)


def covered(start: np.ndarray, end: np.ndarray, w: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs [a, b) of symbols that windows start..end (both included) cover."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    a, b = start[order].astype(np.int64), np.maximum.accumulate(end[order].astype(np.int64) + w)
    new = np.concatenate([[True], a[1:] > b[:-1]])
    return a[new], b[np.concatenate([np.flatnonzero(new)[1:], [len(a)]]) - 1]
