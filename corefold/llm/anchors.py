"""Windows that may repeat, found through content-defined anchors.

A window is `w` consecutive symbols (bytes or words) of one document. Its anchor
is the gram of `k` symbols inside it whose mixed hash is least (the leftmost of
equals). Equal windows have equal anchors at equal offsets, so all occurrences
of a window meet when documents are regrouped by anchor. Neighbouring windows
mostly share their anchor, so one record stands for a run of windows (a
*context*: the symbols from the first window's start to the last one's end).
"""

from __future__ import annotations

import numpy as np

from corefold.llm.common import REMEMBERED

_U = np.uint64
_REMEMBERED = 1 << 20
_POWERS: dict[int, np.ndarray] = {}
REMEMBERED.append(_POWERS)


def powers(base: np.uint64, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64; the first million are remembered."""
    known = _POWERS.get(int(base))
    if known is None or len(known) < n:
        if n > _REMEMBERED:
            return _powers(base, n)
        known = _POWERS[int(base)] = _powers(base, min(_REMEMBERED, max(n, 1 << 16) * 2))
    return known[:n]


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.ones(max(n, 1), dtype=_U)
    done = 1
    step = base
    with np.errstate(over="ignore"):
        while done < n:
            take = min(done, n - done)
            out[done : done + take] = out[:take] * step
            done += take
            step = step * step
    return out[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> _U(31))
        x = x * _U(0xBF58476D1CE4E5B9)
        x ^= x >> _U(27)
        x *= _U(0x94D049BB133111EB)
        x ^= x >> _U(32)
    return x


class Scheme:
    """One way of hashing: a base and a code for each byte. Schemes of different numbers are independent."""

    def __init__(self, number: int):
        salt = _U((number * 2 + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
        self.base = salt | _U(1)
        self.inverse = _U(pow(int(self.base), -1, 1 << 64))
        with np.errstate(over="ignore"):
            self.bytes = mix(np.arange(1, 257, dtype=_U) * _U(0xD6E8FEB86659FD93) + salt)

    def prefix(self, codes: np.ndarray) -> np.ndarray:
        """P[i] = sum of codes[j] * base**j for j < i; one more entry than codes."""
        out = np.zeros(len(codes) + 1, dtype=_U)
        with np.errstate(over="ignore"):
            np.cumsum(codes * powers(self.base, len(codes)), out=out[1:])
        return out

    def spans(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hash of codes[start:end], whatever the position it stands at."""
        with np.errstate(over="ignore"):
            return (prefix[end] - prefix[start]) * powers(self.inverse, len(prefix))[start]


_SCHEMES: dict[int, Scheme] = {}


def scheme(number: int) -> Scheme:
    if number not in _SCHEMES:
        _SCHEMES[number] = Scheme(number)
    return _SCHEMES[number]


def sides(alt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of what stands before and after the anchor, over half of a window's other symbols; 0 where no window of the context goes so far.

    Of a window at least one whole side of its anchor is as long. So contexts that share a
    window share a side that is not 0. `alt` holds them above 32 bits of the whole context.
    """
    return alt >> _U(32) & _U(0xFFFF), alt >> _U(48)


class Anchors:
    """Anchors of one batch of documents, laid end to end.

    `codes`: two independent 64-bit codes of each symbol (by the schemes 2 * seed and
    2 * seed + 1); `begin`: the first symbol of each document, and the total at the end.
    Fields, one entry for each context: `doc` (index in the batch), `first`, `last` (first
    and last window start, counted in the whole batch), `h` (the anchor's hash), `ctx` and
    `alt` (two independent hashes of the context with its anchor's place; see `sides`).
    """

    def __init__(self, codes: tuple[np.ndarray, np.ndarray], begin: np.ndarray, w: int, k: int, seed: int = 0):
        n = len(codes[0])
        empty = np.zeros(0, dtype=np.int64)
        self.doc = self.first = self.last = empty
        self.h = self.ctx = self.alt = np.zeros(0, dtype=_U)
        if n < w:
            return
        one, two = scheme(2 * seed), scheme(2 * seed + 1)
        prefix = one.prefix(codes[0])
        with np.errstate(over="ignore"):
            grams = prefix[k:] - prefix[:-k]
            grams *= powers(one.inverse, n - k + 1)
        grams = mix(grams)
        bits = max(1, int(n).bit_length())
        low = _U((1 << bits) - 1)
        least = grams & ~low
        least |= np.arange(len(grams), dtype=_U)
        width, done = w - k + 1, 1
        while done < width:
            step = min(done, width - done)
            least = np.minimum(least[:-step], least[step:])
            done += step
        least &= low
        at = least.astype(np.int64)  # of the window that starts here
        del least
        lengths = np.diff(begin)
        ends = np.zeros(n + 1, dtype=np.int8)  # 1 where windows may start
        ok = lengths >= w
        np.add.at(ends, begin[:-1][ok], 1)
        np.add.at(ends, (begin[:-1] + lengths - w + 1)[ok], -1)
        valid = np.cumsum(ends[:n], dtype=np.int8)[: len(at)].astype(bool)
        new = np.empty(len(at), dtype=bool)
        new[0] = True
        np.not_equal(at[1:], at[:-1], out=new[1:])
        new[1:] |= ~valid[:-1]
        # a document of exactly w symbols follows another without a gap only if that one had one valid window
        starts_of_docs = begin[:-1][ok]
        new[starts_of_docs] = True
        new &= valid
        self.first = np.flatnonzero(new)
        if not len(self.first):
            return
        gap = np.flatnonzero(~valid)
        stop = np.append(self.first[1:], len(at))
        if len(gap):
            j = np.searchsorted(gap, self.first)
            stop = np.minimum(stop, np.where(j < len(gap), gap[np.minimum(j, len(gap) - 1)], len(at)))
        self.last = stop - 1
        self.h = grams[at[self.first]]
        anchor = at[self.first]
        offset = (anchor - self.first).astype(_U)
        del grams, at, valid, new
        end = self.last + w
        with np.errstate(over="ignore"):
            place = offset * _U(0xA24BAED4963EE407) + (self.last - self.first).astype(_U) * _U(0x9FB21C651E98DF25)
            self.ctx = mix(one.spans(prefix, self.first, end) + place)
            del prefix
            prefix = two.prefix(codes[1])
            self.alt = mix(two.spans(prefix, self.first, end) ^ place) & _U(0xFFFFFFFF)
        half = (w - k + 1) // 2
        for shift, start, inside in ((32, anchor - half, anchor - half >= self.first), (48, anchor + k, anchor + k + half <= end)):
            start = np.where(inside, start, 0)
            side = mix(two.spans(prefix, start, np.where(inside, start + half, 0))) % _U(0xFFFF) + _U(1)
            self.alt |= np.where(inside, side, _U(0)) << _U(shift)
        self.doc = np.searchsorted(begin, self.first, side="right") - 1
