"""Byte-level BPE with a compiled lexicon of frequent words (operator 3).

The lexicon is a minimal acyclic automaton over the UTF-8 bytes of frequent
pretokens: equal suffixes share states. Each state knows how many words end at or
below it, so that a walk also yields the word's number, and a table by number
holds the token ids: together a transducer from words to ids. It is one file, that
each executor has once and all its workers map. Words that it lacks are merged exactly.

Nulls are empty texts. Texts are taken whole, whatever their length.
"""

from __future__ import annotations

import base64
import hashlib
import mmap
from array import array
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corefold.llm.common import REMEMBERED, checkpoint_dir, give_back, slices, text_or_empty, written

#: Words kept in the lexicon, by default.
LEXICON_WORDS = 65_536
#: Remembered words of one worker, in each of two generations, and those that a task counts before it sends them on.
CACHE_WORDS = 300_000
#: Words that occur less often are not worth a place in a lexicon.
LEAST_COUNT = 4


def compile_lexicon(words: dict[bytes, list[int]]) -> bytes:
    """A minimal acyclic transducer of `words` as bytes to be written to a file.

    Layout, all little-endian int64 but where noted: [states, edges, words, ids],
    edge keys (state << 8 | byte, ascending), edge targets, words that are skipped
    when the edge is taken, per state 1 if a word ends there, offsets into the ids
    by word number (one more than words), ids (uint32).
    """
    register: dict[tuple, int] = {}
    states: list[tuple[bool, tuple]] = []

    def settle(node: list) -> int:
        key = (node[0], tuple(node[1]))
        if (found := register.get(key)) is None:
            found = register[key] = len(states)
            states.append(key)
        return found

    # the open path: per depth [a word ends here, settled edges]
    path: list[list] = [[False, []]]
    letters: list[int] = []

    def close(depth: int) -> None:
        while len(path) - 1 > depth:
            node = path.pop()
            path[-1][1].append((letters.pop(), settle(node)))

    for word in sorted(words):
        shared = 0
        for a, b in zip(letters, word, strict=False):
            if a != b:
                break
            shared += 1
        close(shared)
        for byte in word[shared:]:
            letters.append(byte)
            path.append([False, []])
        path[-1][0] = True
    close(0)
    root = settle(path[0])
    below = [0] * len(states)
    for i, (ends, edges) in enumerate(states):  # targets always come first
        below[i] = ends + sum(below[t] for _, t in edges)
    # number the root 0
    order = [root, *(i for i in range(len(states)) if i != root)]
    new = {old: i for i, old in enumerate(order)}
    keys, targets, skips = [], [], []
    final = np.zeros(len(states), dtype="<i8")
    for old in order:
        ends, edges = states[old]
        final[new[old]] = ends
        skip = int(ends)
        for byte, target in sorted(edges):
            keys.append(new[old] << 8 | byte)
            targets.append(new[target])
            skips.append(skip)
            skip += below[target]
    offsets = np.zeros(len(words) + 1, dtype="<i8")
    ids = array("I")
    for i, word in enumerate(sorted(words)):
        ids.extend(words[word])
        offsets[i + 1] = len(ids)
    head = np.array([len(states), len(keys), len(words), len(ids)], dtype="<i8")
    parts = [head, np.array(keys, dtype="<i8"), np.array(targets, dtype="<i8"), np.array(skips, dtype="<i8"), final, offsets, np.array(ids, dtype="<u4")]
    return b"".join(p.tobytes() for p in parts)


class Lexicon:
    """A compiled lexicon, mapped into memory; all processes that map one file share its pages."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self._map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        states, edges, words, ids = np.frombuffer(self._map, "<i8", 4)
        at = 32
        views = []
        for count in (edges, edges, edges, states, words + 1):
            views.append(np.frombuffer(self._map, "<i8", count, at))
            at += 8 * int(count)
        self.keys, self.targets, self.skips, self.final, self.offsets = views
        self.ids = np.frombuffer(self._map, "<u4", ids, at)
        self.words = int(words)

    def numbers(self, words: list[bytes]) -> np.ndarray:
        """The number of each word, or -1; all words walk the automaton together."""
        n = len(words)
        state, number = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
        if not n or not len(self.keys):
            return np.full(n, -1, dtype=np.int64)
        data = np.frombuffer(b"".join(words), dtype=np.uint8)
        size = np.fromiter(map(len, words), dtype=np.int64, count=n)
        begin = np.cumsum(size) - size
        alive = np.flatnonzero(size > 0)
        state[size == 0] = -1
        depth = 0
        while len(alive):
            key = state[alive] << 8 | data[begin[alive] + depth]
            edge = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            good = self.keys[edge] == key
            state[alive[~good]] = -1
            alive, edge = alive[good], edge[good]
            state[alive] = self.targets[edge]
            number[alive] += self.skips[edge]
            depth += 1
            alive = alive[size[alive] > depth]
        ok = (state >= 0) & (self.final[state] == 1)
        return np.where(ok, number, -1)

    def lookup(self, words: list[bytes]) -> list[bytes | None]:
        """Token ids of each word as little-endian uint32, or None."""
        return [None if i < 0 else self.ids[self.offsets[i] : self.offsets[i + 1]].tobytes() for i in self.numbers(words)]


class Vocabulary:
    """Ids and merges of a byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str):
        import json

        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        shown = {b: chr(b) for b in printable}
        shown |= {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in shown)}
        byte_of = {c: b for b, c in shown.items()}
        special = {x["content"]: x["id"] for x in data["added_tokens"]}
        self.special = special
        self.bytes_of: dict[int, bytes] = {i: bytes(byte_of[c] for c in t) for t, i in data["model"]["vocab"].items() if t not in special}
        self.id_of = {b: i for i, b in self.bytes_of.items()}
        self.bytes_of |= {i: t.encode() for t, i in special.items()}
        merges = (m.split(" ") if isinstance(m, str) else m for m in data["model"]["merges"])
        self.rank = {tuple(bytes(byte_of[c] for c in part) for part in m): i for i, m in enumerate(merges)}

    def merge(self, word: bytes) -> list[int]:
        """Exact BPE of one pretoken: always the pair of least rank, leftmost first."""
        parts = [word[i : i + 1] for i in range(len(word))]
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 40))
            if (parts[best], parts[best + 1]) not in self.rank:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return [self.id_of[p] for p in parts]


#: How the byte-level pre-tokenizer splits (fixed value of the public format).
PRETOKENS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class _Clashing(Exception):
    """A chunk that begins or ends with white space: its neighbours matter."""


class Encoder(dict):
    """Whole texts to ids. Maps a chunk to the packed ids of it and the space before it.

    Chunks stand between spaces; a line break counts as a space before it, so "\\nword" is
    a chunk too. A space between non-spaces always begins a pretoken, and so does a line
    break, so chunks with no other white space at their ends can be encoded apart and
    remembered (two generations of CACHE_WORDS); `first` remembers those without a space
    before. Texts with other chunks take the pattern itself.
    """

    def __init__(self, path: str, lexicon: Lexicon | None = None):
        import regex
        import tiktoken

        super().__init__()
        self.vocabulary = Vocabulary(path)
        self.lexicon = lexicon
        self.first: dict[str, bytes] = {}
        self._old: dict[str, bytes] = {}
        ranks = {b: i for b, i in self.vocabulary.id_of.items()}
        self._merge = tiktoken.Encoding("merge", pat_str=PRETOKENS, mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self.pretokens = regex.compile(PRETOKENS).findall
        self._newline = self.slow("\n")
        self._marks = {c: self.slow(c) for c in ".,;:!?"}
        special = self.vocabulary.special
        self._special = regex.compile("(" + "|".join(map(regex.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        most = max(self.vocabulary.bytes_of) + 1
        self._bytes = [self.vocabulary.bytes_of.get(i) for i in range(most)]
        self._names = [str(i) for i in range(most)]

    def slow(self, text: str) -> bytes:
        """Packed ids by the pattern, without remembering anything."""
        return b"".join([array("I", self._merge(p.encode())).tobytes() for p in self.pretokens(text)])

    def _begin(self, chunk: str) -> bytes:
        if (ids := self.first.get(chunk)) is None:
            if len(self.first) > CACHE_WORDS // 4:
                self.first.clear()
            ids = self.first[chunk] = self.slow(chunk)
        return ids

    def _cut(self, chunk: str) -> list[str]:
        """The pretokens of a chunk without white space at its ends, after a space or a line break."""
        if chunk[0] == "\n":
            return ["\n", *self.pretokens(chunk[1:])]
        if chunk.isascii():  # a word, or a word and a mark
            if chunk.isalpha():
                return [" " + chunk]
            if chunk[-1] in self._marks and chunk[:-1].isalpha():
                return [" " + chunk[:-1], chunk[-1]]
        return self.pretokens(" " + chunk)

    def __missing__(self, chunk: str) -> bytes:
        if (ids := self._old.get(chunk)) is None:
            if chunk.isalpha() and chunk.isascii():  # a word
                ids = array("I", self._merge(b" " + chunk.encode())).tobytes()
            elif chunk[-1:] in self._marks and chunk[:-1].isalpha() and chunk.isascii():  # a word and a mark
                ids = self[chunk[:-1]] + self._marks[chunk[-1]]
            elif _clashes(chunk):
                raise _Clashing
            elif chunk[0] == "\n":
                return self._newline + self._begin(chunk[1:])
            else:
                ids = self.slow(" " + chunk)
        self[chunk] = ids
        return ids

    def learn(self, chunks: list[list[str]]) -> None:
        """Look up new chunks in the lexicon, all at once; what it lacks is merged."""
        if len(self) > CACHE_WORDS:  # keep one older generation
            self._old = dict(self)
            self.clear()
        if self.lexicon is None:
            return
        seen: set[str] = set()
        seen.update(*chunks)
        new = [c for c in seen.difference(self) if c not in self._old and not _clashes(c)]
        parts = [self._cut(c) for c in new]
        flat = [p.encode() for ps in parts for p in ps]
        merge = self._merge
        ids = [array("I", merge(p)).tobytes() if g is None else g for g, p in zip(self.lexicon.lookup(flat), flat, strict=True)]
        at = 0
        for chunk, ps in zip(new, parts, strict=True):
            self[chunk] = ids[at] if len(ps) == 1 else b"".join(ids[at : at + len(ps)])
            at += len(ps)

    def _plain(self, text: str, chunks: list[str] | None) -> bytes:
        """Packed ids of a text without special tokens, from its chunks if it has them."""
        if chunks is None:
            return self.slow(text)
        try:
            head = chunks[0]
            if not head and len(text) or head and (head[0].isspace() or head[-1].isspace()):
                raise _Clashing
            body = b"".join(map(self.__getitem__, chunks[1:]))
            return self._begin(head) + body if head else body
        except _Clashing:
            return self.slow(text)

    def encode_all(self, texts: list[str]) -> Iterator[bytes]:
        """Packed ids of each text, as little-endian uint32; each text is cut once."""
        cut = [_chunks(t) for t in texts]
        self.learn([c for c in cut if c is not None])
        special = self.vocabulary.special
        for text, chunks in zip(texts, cut, strict=True):
            if self._special is not None and any(s in text for s in special):
                yield b"".join(array("I", [special[x]]).tobytes() if x in special else self._plain(x, _chunks(x)) for x in self._special.split(text) if x)
            else:
                yield self._plain(text, chunks)

    def encode(self, text: str) -> bytes:
        return next(self.encode_all([text]))

    def decode(self, ids: Iterable[int]) -> str:
        return b"".join(map(self._bytes.__getitem__, ids)).decode("utf-8", "replace")

    def listed(self, ids: Iterable[int]) -> str:
        """Decimal ids joined by commas."""
        return ",".join(map(self._names.__getitem__, ids))


def _chunks(text: str) -> list[str] | None:
    """What stands between spaces; a line break begins a chunk. None if that is not told apart from a space before it."""
    if "\n" in text:
        if " \n" in text:
            return None
        text = text.replace("\n", " \n")
    return text.split(" ")


def _clashes(chunk: str) -> bool:
    if chunk[:1] == "\n":
        chunk = chunk[1:]
    return not chunk or chunk[0].isspace() or chunk[-1].isspace()


_ENCODERS: dict = {}
REMEMBERED.append(_ENCODERS)


def encoder(path: str, lexicon: str | None = None) -> Encoder:
    """One encoder for each worker process; its memory of words serves all its tasks. lexicon: the name of a file that `share` made."""
    if (path, lexicon) not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[path, lexicon] = Encoder(path, Lexicon(SparkFiles.get(lexicon)) if lexicon else None)
    return _ENCODERS[path, lexicon]


def share(spark: SparkSession, blob: bytes) -> str:
    """Put a lexicon into the shared checkpoint folder and have each executor fetch it once; returns its file's name."""
    name = f"lexicon-{hashlib.sha256(blob).hexdigest()}"
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{checkpoint_dir(spark)}/{name}")
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.exists(path):
        out = fs.create(path, True)
        out.write(blob)
        out.close()
    spark.sparkContext.addFile(str(path.toString()))
    return name


def frequent_words(texts: DataFrame, column: str, words: int) -> list[str]:
    """The most frequent chunks between white space over all texts, at most `words`; counted per task first, then by word."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(list(counts), pa.string()), pa.array(list(counts.values()), pa.int64())], names=["word", "n"])
            counts.clear()
            return out

        for batch in batches:
            for text in batch.column(0).to_pylist():
                counts.update(text.split())
                if len(counts) > CACHE_WORDS:
                    yield flush()
        if counts:
            yield flush()

    found = texts.select(text_or_empty(column).alias("t")).mapInArrow(count, "word string, n long")
    counts = written(found.groupBy("word").agg(F.sum("n").alias("n")).filter(F.col("n") >= LEAST_COUNT))
    # the count that at most `words` words reach: from words by count, then only these words come to the driver
    by_count = counts.groupBy(F.floor(F.log(2.0, "n") * 64).alias("level")).agg(F.count("*").alias("words"), F.min("n").alias("n"))
    least, total = None, 0
    for r in sorted(by_count.collect(), key=lambda r: -r.level):  # 64 levels for each doubling
        if (total := total + r.words) > words:
            break
        least = r.n
    return [] if least is None else [r.word for r in counts.filter(F.col("n") >= least).collect()]


def build_lexicon(texts: DataFrame, column: str, path: str, words: int = LEXICON_WORDS) -> bytes:
    enc = Encoder(path)
    out: dict[bytes, list[int]] = {}
    for word in frequent_words(texts, column, words):
        for chunk in (word, " " + word):
            for piece in enc.pretokens(chunk):
                out.setdefault(piece.encode(), enc._merge(piece.encode()))
    return compile_lexicon(out)


def encode_decode(docs: DataFrame, path: str, words: int = LEXICON_WORDS, keep_ids: bool = False) -> DataFrame:
    """Encode every text and decode its ids again.

    Returns doc_id, n_tokens, ids_sha256, decoded_sha256; with `keep_ids` also ids
    (array of ints) and decoded (string). A null text is empty; a null doc_id stays null.
    """
    name = share(docs.sparkSession, build_lexicon(docs, "text", path, words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, name)
        for whole in batches:
            for batch in slices(whole, "text", 4 << 20):
                out: list[list] = [[], [], [], [], []]
                for packed in enc.encode_all(batch.column(1).to_pylist()):
                    ids = array("I", packed).tolist()
                    decoded = enc.decode(ids)
                    out[0].append(len(ids))
                    out[1].append(hashlib.sha256(enc.listed(ids).encode()).hexdigest())
                    out[2].append(hashlib.sha256(decoded.encode()).hexdigest())
                    if keep_ids:
                        out[3].append(ids)
                        out[4].append(decoded)
                columns = [batch.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.string()), pa.array(out[2], pa.string())]
                if keep_ids:
                    columns += [pa.array(out[3], pa.list_(pa.int32())), pa.array(out[4], pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"]
                yield pa.RecordBatch.from_arrays(columns, names=names[: len(columns)])
        give_back()

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * keep_ids
    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(run, schema)
