"""Repeated passages by De Bruijn compaction (operator 10).

A window of `w` words is an edge from its first w-1 words to its last w-1. Edges are
kept in runs that share an anchor word-gram, so a run that stands elsewhere as a whole
is a path that has been compacted without ever naming its edges. Runs that share their
anchor but differ are taken apart into edges, and these are matched one by one. What
repeats is a set of pieces with source coordinates: where the words stand, and the
earliest place where they also stand. Pieces that follow one another in documents are
arcs of the graph; joins find arcs with one way in and one way out and compact them to
paths. A document's walks along paths are the spans that are removed. Each piece's words
are compared with those at its source coordinates; should different words ever have met
under their two 64-bit hashes, everything is done again with other hashes.

Removed is every word in a window that also starts in a document with a smaller doc_id.

A null text has no words; shorter documents than a window repeat nothing. Rows without
doc_id are earlier or later than no other and stay whole. Rows that share a doc_id are
one document, which never repeats itself.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corefold.llm import windows
from corefold.llm.anchors import mix, scheme
from corefold.llm.common import give_back, partitions_for, slices, text_or_empty, written

EDGE = np.dtype([("edge", "<u8"), ("alt", "<u8"), ("doc", "<i8"), ("tid", "<i8"), ("first", "<i4")])
PIECE = "doc_id long, tid long, start int, end int, src_doc long, src_tid long, src_start int"


def edge_parts(docs: DataFrame, found: DataFrame, spec: windows.Spec, parts: int) -> DataFrame:
    """The edges of open runs, by their hash; what a task can tell to repeat, by document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mask = np.uint64((1 << spec.bits) - 1)
        for whole in batches:
            for batch in slices(whole, "text", windows.SLICE):
                codes, begin = windows.symbols([t.encode() for t in batch.column(2).to_pylist()], spec.words, spec.seed)
                starts, docs_, tids = [], [], []
                for i, blob in enumerate(batch.column(3).to_pylist()):
                    runs = np.frombuffer(blob, dtype=windows.OPEN)
                    sizes = runs["n"].astype(np.int64) + 1
                    within = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                    starts.append(np.repeat(runs["first"].astype(np.int64), sizes) + within + begin[i])
                    docs_.append(np.full(len(within), batch.column(0)[i].as_py(), dtype=np.int64))
                    tids.append(np.full(len(within), batch.column(1)[i].as_py(), dtype=np.int64))
                at, doc, tid = np.concatenate(starts), np.concatenate(docs_), np.concatenate(tids)
                hashes = []
                for own, c in zip((scheme(2 * spec.seed), scheme(2 * spec.seed + 1)), codes, strict=True):
                    hashes.append(mix(own.spans(own.prefix(c), at, at + spec.w)) & mask)
                first = (at - np.repeat(begin[:-1], [len(x) for x in starts])).astype(np.int32)
                x = windows.records(EDGE, *hashes, doc, tid, first)
                c = windows.classes(tuple(hashes), doc, first, spec.by_doc)
                yield from windows.send_repeats(parts, c, doc, tid, first, np.zeros(len(first), dtype=np.int32))
                x = x[np.sort(c.order[~c.repeat])]
                yield from windows.by_part(mix(x["edge"]) % np.uint64(parts), windows.PIECES, x)
        give_back()

    return windows.map_joined(docs, found.filter(F.length("open") > 0).select("doc_id", "tid", "open"), run, windows.PACKED, "inner")


def match_edges(packed: DataFrame, spec: windows.Spec, parts: int) -> DataFrame:
    """Edges that stand in an earlier document too, as pieces by document."""

    def run(table: pa.Table) -> pa.Table:
        out = windows.passed_on(table, windows.REPEATS)
        x = windows.gather(table, windows.PIECES, EDGE)
        if len(x):
            c = windows.classes((np.ascontiguousarray(x["edge"]), x["alt"]), x["doc"], x["first"], spec.by_doc)
            out += windows.send_repeats(parts, c, x["doc"], x["tid"], x["first"], np.zeros(len(x), dtype=np.int32))
        return windows.sent(out)

    return packed.groupBy("part").applyInArrow(run, windows.PACKED)


def pieces(found: DataFrame) -> DataFrame:
    """One row for each piece: where it stands, and its source."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            blobs = batch.column(2).to_pylist()
            spans = np.frombuffer(b"".join(blobs), dtype=windows.SPAN)
            sizes = [len(b) // windows.SPAN.itemsize for b in blobs]
            ids = [pa.array(np.repeat(batch.column(i).to_numpy(), sizes)) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([*ids, *(pa.array(np.ascontiguousarray(spans[f])) for f in windows.SPAN.names)], names=["doc_id", "tid", *windows.SPAN.names])

    return found.select("doc_id", "tid", "spans").filter(F.length("spans") > 0).mapInArrow(run, PIECE)


def compact(parts: DataFrame) -> DataFrame:
    """parts with `node` (their source's coordinates) and `path`: the node that begins their nonbranching path.

    An arc u -> v is compacted if u has no other way out and v no other way in. Heads are
    found by doubling: each round every node adopts its predecessor's predecessor.
    """
    named = written(parts.withColumn("node", F.xxhash64("src_doc", "src_tid", "src_start", F.col("end") - F.col("start"))))
    after = named.select("doc_id", "tid", F.col("start").alias("at"), F.col("node").alias("v"))
    arcs = written(named.select("doc_id", "tid", (F.col("end") + 1).alias("at"), F.col("node").alias("u")).join(after, ["doc_id", "tid", "at"]).select("u", "v").distinct())
    one_out = arcs.groupBy("u").agg(F.count("*").alias("n"), F.first("v").alias("v")).filter("n = 1 AND u <> v").select("u", "v")
    one_in = arcs.groupBy("v").agg(F.count("*").alias("n")).filter("n = 1").select("v")
    heads = written(one_out.join(one_in, "v").select("v", F.col("u").alias("head")))
    rounds = max(1, heads.count()).bit_length() + 1  # enough for any chain; a ring never ends by itself
    for _ in range(rounds):
        up = heads.select(F.col("v").alias("head"), F.col("head").alias("next"))
        moved = heads.join(up, "head", "left")
        if moved.filter("next IS NOT NULL").isEmpty():
            break
        heads = written(moved.select("v", F.coalesce("next", "head").alias("head")))
    return named.join(heads.withColumnRenamed("v", "node"), "node", "left").withColumn("path", F.coalesce("head", "node")).drop("head")


def walks(compacted: DataFrame) -> DataFrame:
    """doc_id, tid, path, start, end: the runs of pieces along one path, without a gap; windows start..end repeat."""
    along = Window.partitionBy("doc_id", "tid", "path").orderBy("start", "end")
    reach = F.max("end").over(along.rowsBetween(Window.unboundedPreceding, -1))
    marked = compacted.select("doc_id", "tid", "path", "start", "end", F.when(F.col("start") <= reach + 1, 0).otherwise(1).alias("new"))
    numbered = marked.withColumn("walk", F.sum("new").over(along.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("doc_id", "tid", "path", "walk").agg(F.min("start").alias("start"), F.max("end").alias("end"))


def remove_repeats(docs: DataFrame, w: int = 50, k: int = 16, **limits: int) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, n_paths (compacted paths that the document shares), text (what is kept).

    limits: hot, heavy, flush, seed, bits (see windows.Spec).
    """
    for seed in count(limits.pop("seed", 0)):
        spec = windows.Spec(w, k, words=True, by_doc=True, seed=seed, **limits)
        cleaned = written(_removed(docs, spec))
        if _as_at_source(cleaned):
            return cleaned.drop("own", "asked")
        limits.pop("bits", None)  # whole hashes from now on


def _removed(docs: DataFrame, spec: windows.Spec) -> DataFrame:
    parts = partitions_for(docs, 8 << 20)
    known = windows.identified(docs)
    found = windows.repeated(known, spec, parts)
    edges = written(windows.by_document(match_edges(edge_parts(known, found, spec, parts), spec, parts)))
    compacted = written(compact(pieces(found).unionByName(pieces(edges))), instead_of=[found, edges])
    spans = walks(compacted).groupBy("doc_id", "tid").agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("spans"), F.count_distinct("path").alias("n_paths"))
    own = compacted.groupBy("doc_id", "tid").agg(F.collect_list(F.struct("start", "end", "node")).alias("own"))
    # one request for each different span of a source, however many documents repeat it
    asked = compacted.select(F.col("src_doc").alias("doc_id"), F.col("src_tid").alias("tid"), F.col("src_start").alias("start"), (F.col("src_start") + F.col("end") - F.col("start")).alias("end"), "node").distinct()
    asked = asked.groupBy("doc_id", "tid").agg(F.collect_list(F.struct("start", "end", "node")).alias("asked"))
    wanted = spans.join(own, ["doc_id", "tid"]).join(asked, ["doc_id", "tid"], "full")
    w = spec.w

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        def digests(ws: list[bytes], asked: list[dict] | None) -> list[dict]:
            return [{"node": x["node"], "hash": xxhash.xxh3_128_digest(b" ".join(ws[x["start"] : x["end"] + w]))} for x in asked or ()]

        for whole in batches:
            for batch in slices(whole, "text", 2 << 20):
                rows: list[list] = [[], [], [], [], [], []]
                for text, gone, mine, theirs in zip(*(batch.column(i).to_pylist() for i in (2, 3, 4, 5)), strict=True):
                    ws = text.encode().split()
                    a, b = windows.covered(np.array([x["start"] for x in gone or ()]), np.array([x["end"] for x in gone or ()]), w)
                    kept, at = [], 0
                    for x, y in zip(a.tolist(), b.tolist(), strict=True):
                        kept += ws[at:x]
                        at = y
                    kept += ws[at:]
                    joined = b" ".join(kept)
                    for column, value in zip(rows, (len(ws), len(ws) - len(kept), hashlib.sha256(joined).hexdigest(), digests(ws, mine), digests(ws, theirs), joined.decode()), strict=True):
                        column.append(value)
                pair = pa.list_(pa.struct([("node", pa.int64()), ("hash", pa.binary())]))
                kinds = (pa.int64(), pa.int64(), pa.string(), pair, pair, pa.string())
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(6), *map(pa.array, rows, kinds)], names=["doc_id", "n_paths", "n_words", "n_removed", "kept_sha256", "own", "asked", "text"])
        give_back()

    pairs = "array<struct<node:long,hash:binary>>"
    everything = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).withColumn("tid", F.xxhash64("text"))
    cleaned = windows.map_joined(everything, wanted.select("doc_id", "tid", "spans", "own", "asked", "n_paths"), run, f"doc_id long, n_paths long, n_words long, n_removed long, kept_sha256 string, own {pairs}, asked {pairs}, text string", "left")
    return cleaned.withColumn("n_paths", F.coalesce("n_paths", F.lit(0).cast("long")))


def _as_at_source(cleaned: DataFrame) -> bool:
    """Whether every piece holds the words that stand at its source coordinates."""
    there = cleaned.select(F.explode("asked").alias("x")).select("x.node", F.col("x.hash").alias("there"))
    here = cleaned.select(F.explode("own").alias("x")).select("x.node", F.col("x.hash").alias("here")).distinct()
    return here.join(there, "node", "left").filter("NOT (here <=> there)").isEmpty()
