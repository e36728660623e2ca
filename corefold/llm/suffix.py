"""External induced sorting of suffixes, with common prefixes (for operator 2).

Suffixes are sorted by their first `cap` symbols at least; equal ones stand in any
order. The steps are those of induced sorting: suffixes that begin a valley (LMS) are
named by the text up to the next valley, the shorter text of names is sorted in turn,
and from its order all other suffixes are induced in two sweeps over the buckets of
first bytes. A sweep takes a bucket's tuples (place, common prefix with the tuple
before) in waves and sends each to the bucket of the byte before it, where tuples
arrive in order; so a priority queue by (byte, order of arrival) is all that is needed.
Its tuples go to disk whenever they exceed a given memory. A tuple's common prefix is
one more than the least of those between it and the last tuple sent to its bucket.
"""

from __future__ import annotations

import tempfile

import numpy as np


class DiskQueue:
    """First in, first out for each of 256 keys; beyond `memory` bytes the fullest key's tuples go to a file."""

    def __init__(self, memory: int):
        self.memory = memory
        self._held: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in range(256)]
        self._size = np.zeros(256, dtype=np.int64)
        self._file = None
        self._runs: list[list[tuple[int, int]]] = [[] for _ in range(256)]

    def push(self, key: int, place: np.ndarray, common: np.ndarray) -> None:
        self._held[key].append((place, common))
        self._size[key] += 5 * len(place)
        while self._size.sum() > self.memory:
            self._spill(int(np.argmax(self._size)))

    def _spill(self, key: int) -> None:
        if self._file is None:
            self._file = tempfile.TemporaryFile(prefix="suffix-queue-")  # noqa: SIM115  lives as long as the queue; has no name
        place, common = (np.concatenate(c) for c in zip(*self._held[key], strict=True))
        self._file.seek(0, 2)
        self._runs[key].append((self._file.tell(), len(place)))
        self._file.write(place.astype("<i4").tobytes())
        self._file.write(common.astype("u1").tobytes())
        self._held[key].clear()
        self._size[key] = 0

    def pop(self, key: int) -> tuple[np.ndarray, np.ndarray] | None:
        """All tuples of the key, in the order they came."""
        found = []
        for at, n in self._runs[key]:
            self._file.seek(at)
            found.append((np.frombuffer(self._file.read(4 * n), "<i4"), np.frombuffer(self._file.read(n), "u1")))
        found += self._held[key]
        self._runs[key], self._held[key] = [], []
        self._size[key] = 0
        if not found:
            return None
        return found[0] if len(found) == 1 else tuple(np.concatenate(c) for c in zip(*found, strict=True))


class Text:
    """Bytes 1..255, with a 0 after each part; and whether each suffix is less than the next (valley side)."""

    def __init__(self, data: np.ndarray, cap: int):
        if cap > 250:
            raise ValueError("common prefixes are held in one byte")
        self.n, self.cap = len(data), cap
        padded = np.zeros(self.n + cap + 16, dtype=np.uint8)
        padded[: self.n] = data
        self.data = padded[: self.n]
        self._eight = np.ndarray((self.n + cap + 8,), dtype=">u8", buffer=padded, strides=(1,))
        rise = np.zeros(self.n, dtype=bool)
        differ = np.flatnonzero(self.data[1:] != self.data[:-1])
        up = self.data[differ + 1] > self.data[differ]
        begin = np.concatenate([[0], differ + 1])
        for_run = np.concatenate([up, [False]])  # the last run falls to the empty suffix
        rise = np.repeat(for_run, np.diff(np.concatenate([begin, [self.n]])))
        self.rise = rise

    def common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Common prefix of the suffixes at a and b, at most cap."""
        out = np.full(len(a), self.cap, dtype=np.uint8)
        todo = np.arange(len(a))
        for at in range(0, self.cap, 8):
            x = self._eight[a[todo] + at].astype(np.uint64) ^ self._eight[b[todo] + at].astype(np.uint64)
            found = x != 0
            y, zero = x[found], np.full(int(found.sum()), at, dtype=np.int64)
            for bits in (32, 16, 8):
                low = y < np.uint64(1 << (64 - bits))
                zero += np.where(low, bits // 8, 0)
                y = np.where(low, y << np.uint64(bits), y)
            out[todo[found]] = np.minimum(zero, self.cap)
            todo = todo[~found]
            if not len(todo):
                break
        return np.minimum(out, self.n - np.maximum(a, b)).astype(np.uint8)


def _dense(keys: np.ndarray) -> np.ndarray:
    order = np.argsort(keys)
    s = keys[order]
    rank = np.zeros(len(keys), dtype=np.int64)
    rank[order] = np.cumsum(np.concatenate([[0], s[1:] != s[:-1]])) + 1
    return rank


def sorted_valleys(text: Text) -> np.ndarray:
    """LMS places in the order of their suffixes."""
    valley = np.flatnonzero(text.rise[1:] & ~text.rise[:-1]) + 1
    if len(valley) < 2:
        return valley.astype(np.int32)
    # names: (byte, side) up to and with the next valley; no such string begins another
    end = np.concatenate([valley[1:], [text.n - 1]])
    length = end - valley + 1
    code = np.zeros(text.n + 8, dtype=np.uint64)
    code[: text.n] = (text.data.astype(np.uint64) << np.uint64(1) | text.rise) + np.uint64(1)
    name = np.zeros(len(valley), dtype=np.int64)
    todo, at = np.arange(len(valley)), 0
    while len(todo):
        word = np.zeros(len(todo), dtype=np.uint64)
        for j in range(6):
            inside = at + j < length[todo]
            word = word << np.uint64(10) | np.where(inside, code[np.minimum(valley[todo] + at + j, text.n)], np.uint64(0))
        if at == 0:
            name = _dense(word)
        else:
            part = _dense(word)
            refined = name * np.int64(len(valley) + 1)
            refined[todo] += part
            name = _dense(refined)
        at += 6
        todo = todo[length[todo] > at]
    # the text of names, sorted by doubling; a name is two bytes or more, so cap / 2 names reach far enough
    step = 1
    while 2 * step < text.cap and name.max() < len(name):
        after = np.zeros(len(name), dtype=np.int64)
        after[:-step] = name[step:]
        name = _dense(name * np.int64(len(name) + 1) + after)
        step *= 2
    return valley[np.argsort(name, kind="stable")].astype(np.int32)


class _Sweep:
    """One direction of the induction."""

    def __init__(self, text: Text, rising: bool, memory: int):
        self.text, self.rising = text, rising
        self.queue = DiskQueue(memory)
        self.least = np.full(256, text.cap, dtype=np.uint8)  # since the last tuple sent to each bucket
        self.sent = np.zeros(256, dtype=bool)

    def feed(self, place: np.ndarray, common: np.ndarray) -> None:
        """Send the suffixes before these, if they are of this sweep's side."""
        text = self.text
        if not len(place):
            return
        before = place - 1
        ok = (place > 0) & (text.rise[before] == self.rising)
        at = np.flatnonzero(ok)
        everywhere = common.min()
        if not len(at):
            np.minimum(self.least, everywhere, out=self.least)
            return
        key = text.data[before[at]]
        order = np.argsort(key, kind="stable")
        key, at = key[order], at[order]
        head = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        begin = np.empty(len(at), dtype=np.int64)
        begin[1:] = at[:-1] + 1
        begin[head] = 0
        padded = np.append(common, np.uint8(255))
        spans = np.empty(2 * len(at), dtype=np.int64)
        spans[0::2], spans[1::2] = begin, at + 1
        value = np.minimum.reduceat(padded, spans)[0::2].astype(np.int16)
        keys = key[head]
        value[head] = np.minimum(value[head], self.least[keys])
        value = np.minimum(value + 1, text.cap)
        value[head[~self.sent[keys]]] = 0
        value = value.astype(np.uint8)
        bounds = np.append(head, len(at))
        tail = np.append(np.minimum.accumulate(common[::-1])[::-1], np.uint8(255))
        np.minimum(self.least, everywhere, out=self.least)
        self.least[keys] = tail[at[bounds[1:] - 1] + 1]
        self.sent[keys] = True
        sent = before[at]
        for k, a, b in zip(keys.tolist(), bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            self.queue.push(k, sent[a:b], value[a:b])

    def drain(self, key: int) -> tuple[np.ndarray, np.ndarray]:
        """The bucket's tuples; those they send to it themselves follow in waves."""
        found = []
        while (wave := self.queue.pop(key)) is not None:
            found.append(wave)
            self.feed(*wave)
        if not found:
            return np.zeros(0, dtype=np.int32), np.zeros(0, dtype=np.uint8)
        return found[0] if len(found) == 1 else tuple(np.concatenate(c) for c in zip(*found, strict=True))


def sorted_suffixes(data: np.ndarray, cap: int, memory: int = 64 << 20) -> tuple[np.ndarray, np.ndarray]:
    """(places in order, common prefix of each with the one before), prefixes up to cap."""
    text = Text(data, cap)
    none = np.zeros(0, dtype=np.int32), np.zeros(0, dtype=np.uint8)
    if not text.n:
        return none
    valleys = sorted_valleys(text)
    shared = np.zeros(len(valleys), dtype=np.uint8)
    if len(valleys) > 1:
        shared[1:] = text.common(valleys[:-1], valleys[1:])
    first = text.data[valleys]
    cut = np.searchsorted(first, np.arange(257))
    one = lambda a, b: text.common(np.array([a]), np.array([b]))[0]
    down = _Sweep(text, False, memory)
    down.queue.push(int(text.data[-1]), np.array([text.n - 1], dtype=np.int32), np.zeros(1, dtype=np.uint8))
    down.sent[text.data[-1]] = True
    falling = []
    for key in range(256):
        place, common = down.drain(key)
        falling.append((place, common))
        own, prefix = valleys[cut[key] : cut[key + 1]], shared[cut[key] : cut[key + 1]].copy()
        if len(own):
            prefix[0] = one(place[-1], own[0]) if len(place) else 0
            down.feed(own, prefix)
    del valleys, shared
    up = _Sweep(text, True, memory)
    parts: list[tuple[np.ndarray, np.ndarray]] = []
    for key in range(255, -1, -1):
        rising, common = up.drain(key)
        place, prefix = falling.pop()
        if len(place):
            edge = one(place[-1], rising[-1]) if len(rising) else np.uint8(0)
            up.feed(place[::-1], np.concatenate([[edge], prefix[:0:-1]]).astype(np.uint8))
        else:
            edge = np.uint8(0)
        if len(rising):
            parts.append((rising[::-1], np.concatenate([[edge], common[:0:-1]]).astype(np.uint8)))
        if len(place):
            parts.append((place, prefix))
    return tuple(np.concatenate(c) for c in zip(*reversed(parts), strict=True)) if parts else none
