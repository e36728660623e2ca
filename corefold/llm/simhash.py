"""SimHash fingerprints and near-duplicate classes by pigeonhole blocks (operator 9).

Fingerprints are cut into `distance` + 2 blocks, so two that differ in at most
`distance` bits agree in at least two blocks: candidates are those that share a pair
of blocks. Equal fingerprints are one node from the start, so copies cost nothing.

Within a pair of blocks groups up to some thousands are compared in memory, and only a
forest of their links leaves the task. Larger ones never come together: there each fingerprint names its neighbourhood instead - itself with each choice of
`distance` of the remaining bits set to zero, and which bits these were. Two share such
a name exactly if they are within the distance. Each name links its members to its
least, which joins what all pairs would join, in rows linear in the members.

Words and shingles are as in the query's contract. A null text is empty; an empty text
has fingerprint zero. Rows without doc_id get a null component and link nothing.
Rows that repeat a doc_id are one document for each different fingerprint.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corefold.llm.common import give_back, slices, text_or_empty, written


def shingles(text: str, size: int) -> Iterable[bytes]:
    """Runs of `size` words; of fewer words one run, of none no run."""
    words = text.encode().lower().split()  # bytes: only A-Z and ASCII white space
    if not words:
        return []
    return map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False)) if len(words) >= size else [b" ".join(words)]


def fingerprint(text: str, size: int = 3) -> int:
    """Of one text: the bits that more than half of the shingles' hashes have."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter([digest(s, 42) for s in shingles(text, size)], dtype=np.uint64)
    if not len(hashes):
        return 0
    return int(majority(hashes, np.array([0, len(hashes)]))[0])


def majority(hashes: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """For each run hashes[begin[i]:begin[i+1]] (none empty) the bits set in over half of it."""
    bits = np.unpackbits(hashes.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
    out = np.empty((len(begin) - 1, 64), dtype=bool)
    for i in range(len(begin) - 1):
        out[i] = 2 * bits[begin[i] : begin[i + 1]].sum(axis=0, dtype=np.int64) > begin[i + 1] - begin[i]
    return np.packbits(out, axis=1).view(">u8").astype(np.uint64).ravel()


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """doc_id, fp (the 64 bits as a long), tid (a hash of the text, to tell apart rows that share a doc_id)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text", 2 << 20):
                fps = np.array([fingerprint(t, size) for t in batch.column(1).to_pylist()], dtype=np.uint64)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64)), batch.column(2)], names=["doc_id", "fp", "tid"])
        give_back()

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    return chosen.withColumn("tid", F.xxhash64("text")).select("doc_id", "text", "tid").mapInArrow(run, "doc_id long, fp long, tid long")


def block_masks(distance: int) -> list[int]:
    """For each pair of blocks the bits that both hold."""
    blocks = distance + 2
    edges = [64 * i // blocks for i in range(blocks + 1)]
    masks = [sum(1 << b for b in range(edges[i], edges[i + 1])) for i in range(blocks)]
    return [a | b for a, b in combinations(masks, 2)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def _names(free: int, distance: int) -> np.ndarray:
    """Every choice of `distance` of the bits in `free`, as masks."""
    bits = [1 << b for b in range(64) if free >> b & 1]
    return np.array([sum(c) for c in combinations(bits, distance)], dtype=np.uint64)


def near_forest(fps: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """Edges (first member, other member) of the classes that links within the distance make of one group."""
    root = np.arange(len(fps))
    for i in range(len(fps) - 1):
        near = np.flatnonzero(np.bitwise_count(fps[i + 1 :] ^ fps[i]) <= distance) + i + 1
        if len(near):
            met = np.unique(root[np.append(near, i)])
            if len(met) > 1:
                root[np.isin(root, met)] = met[0]
    return [(int(r), j) for j, r in enumerate(root.tolist()) if r != j]


def links(fps: DataFrame, distance: int = 2, pairwise: int | None = None) -> DataFrame:
    """Pairs (a, b) of different fingerprints that join all fingerprints within `distance` of each other.

    fps: fp long, each once. Both ends are always in one class of such links; there are
    at most as many pairs as members in each group, never all pairs of a group.
    """
    masks = block_masks(distance)
    if pairwise is None:  # from here on names are fewer than comparisons
        pairwise = 2 * max(comb(64 - m.bit_count(), distance) for m in masks)
    keyed = fps.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in masks])).alias("mask", "key"))
    sizes = keyed.groupBy("mask", "key").agg(F.count("*").alias("n")).filter("n > 1")
    shared = written(keyed.join(sizes, ["mask", "key"]))
    small = shared.filter(F.col("n") <= pairwise).groupBy("mask", "key").agg(F.sort_array(F.collect_list("fp")).alias("fps")).select("fps")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(0)
            offsets, flat = column.offsets.to_numpy(), column.values.to_numpy()
            unsigned, a, b = flat.view(np.uint64), [], []
            for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                for i, j in near_forest(unsigned[x:y], distance):
                    a.append(flat[x + i])
                    b.append(flat[x + j])
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    pairs = small.mapInArrow(compare, "a long, b long")
    free = [((1 << 64) - 1) ^ m for m in masks]

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        choices = [_names(f, distance) for f in free]
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                mask, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64)
                for m in np.unique(mask):
                    own = fp[mask == m]
                    kept = own[:, None] & ~choices[m][None, :]
                    cleared = np.broadcast_to(choices[m], kept.shape)
                    flat = [np.ascontiguousarray(x).ravel().view(np.int64) for x in (np.repeat(own, len(choices[m])), kept, cleared)]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in flat], names=["fp", "kept", "cleared"])

    large = shared.filter(F.col("n") > pairwise).select("mask", "fp").mapInArrow(name, "fp long, kept long, cleared long").groupBy("kept", "cleared")
    stars = shared.filter(F.col("n") > pairwise).select("mask", "fp").mapInArrow(name, "fp long, kept long, cleared long")
    least = large.agg(F.min("fp").alias("a"), F.max("fp").alias("z")).filter("a < z").select("kept", "cleared", "a")
    # Names are many times the fingerprints they come from, so their size on disk must not lead to a broadcast.
    joined = stars.hint("merge").join(least, ["kept", "cleared"]).filter("a <> fp").select("a", F.col("fp").alias("b"))
    return pairs.unionByName(joined).distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, root: the least node of each connected component, of all nodes that have an edge.

    Alternating large and small stars: each round hangs neighbours under the least one
    known, which halves paths; rounds grow with the logarithm of a component's size.
    A star's rows are counted by edges, so a hot node's are merged before the shuffle.
    """
    edges = written(edges.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).filter("u < v").distinct())
    # each round is written instead of the last
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("m").alias("u"), "v").filter("u < v").distinct()
        # small star: every node and its smaller neighbours go under the least of these
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        small = large.join(low, "v")
        new = written(small.select(F.col("m").alias("u"), "v").unionByName(small.filter("u > m").select(F.col("m").alias("u"), F.col("u").alias("v"))).distinct(), instead_of=[edges])
        # done when every node has one parent, which is no one's child
        again = new.groupBy("v").count().filter("count > 1").select("v").unionByName(new.select(F.col("u").alias("v")).join(new.select("v"), "v", "left_semi"))
        if again.isEmpty():
            return new.select(F.col("v").alias("node"), F.col("u").alias("root")).unionByName(new.select(F.col("u").alias("node"), F.col("u").alias("root")).distinct())
        edges = new


def near_duplicates(docs: DataFrame, size: int = 3, distance: int = 2) -> DataFrame:
    """doc_id, fingerprint (hex), component_id: the least doc_id that links reach; tid."""
    printed = written(fingerprints(docs, size))
    known = written(printed.filter("doc_id IS NOT NULL").groupBy("fp").agg(F.min("doc_id").alias("first")))
    found = components(links(known.select("fp"), distance))
    joined = known.join(found, known.fp == found.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    ids = joined.groupBy("root").agg(F.min("first").alias("component_id"))
    classes = joined.join(ids, "root").select("fp", "component_id")
    out = printed.join(classes, "fp", "left")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"), "tid")


def deduplicate(docs: DataFrame, size: int = 5, distance: int = 3) -> DataFrame:
    """One row of each class: that of the least doc_id. Rows without doc_id all stay."""
    marked = near_duplicates(docs, size, distance).filter("doc_id = component_id")
    first = marked.groupBy("component_id").agg(F.min(F.struct("doc_id", "tid")).alias("x")).select(F.col("x.doc_id").alias("doc"), F.col("x.tid").alias("tid"))
    return first_rows(docs, first)


def first_rows(docs: DataFrame, first: DataFrame) -> DataFrame:
    """One row of docs for each (doc, tid) of `first`, and all without doc_id."""
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("own"), F.xxhash64(text_or_empty()).alias("own_tid"))
    held = rows.filter("own IS NOT NULL").join(first, (F.col("own") == F.col("doc")) & (F.col("own_tid") == F.col("tid")))
    held = held.withColumn("n", F.row_number().over(Window.partitionBy("doc", "tid").orderBy("own"))).filter("n = 1")
    return held.select("row.*").unionByName(docs.filter("doc_id IS NULL"))
