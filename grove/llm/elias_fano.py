"""Elias-Fano sequences in flat files, queried in bulk.

A monotone sequence of n integers below u takes about 2 + log2(u / n) bits each: low
parts packed, high parts as a bit vector in which the i-th one stands at high + i.
Queries come as arrays, and every step is a vectorised pass over all of them.
"""

from __future__ import annotations

import numpy as np

#: Queries are answered in pieces that stay in a processor's cache.
STEP = 1 << 14
_ONE = np.uint64(1)
_BITS = np.array([bin(i).count("1") for i in range(256)], np.uint8)
_NTH = np.full((256, 8), 8, np.uint8)
for _b in range(256):
    _at = [i for i in range(8) if _b >> i & 1]
    _NTH[_b, : len(_at)] = _at


def _or_into(words: np.ndarray, at: np.ndarray, bits: np.ndarray) -> None:
    """words[at] |= bits for rising ``at`` with repeats."""
    if len(at):
        first = np.flatnonzero(np.diff(at, prepend=-1))
        words[at[first]] |= np.bitwise_or.reduceat(bits, first)


class EliasFano:
    """Arrays: head (n, low bits, high limit), high words, low words, ones before each 8 words."""

    def __init__(self, head: np.ndarray, high: np.ndarray, low: np.ndarray, ones: np.ndarray):
        self.n, self.bits, self.top = (int(x) for x in head)
        self.high, self.low, self.ones = high, low, ones
        self.zeros = np.arange(len(ones), dtype=np.int64) * 512 - ones.astype(np.int64)
        self.mask = np.uint64((1 << self.bits) - 1)

    @classmethod
    def build(cls, values: np.ndarray, universe: int) -> EliasFano:
        values = np.ascontiguousarray(values, np.uint64)
        n = len(values)
        bits = max(0, (universe // n).bit_length() - 1) if n else 0
        bits = min(bits, 63)
        top = (universe - 1 >> bits) if universe else 0
        if n == 0:
            top = 0
        size = (n + top + 2 + 511) // 512 * 8
        high = np.zeros(size, np.uint64)
        at = (values >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        _or_into(high, at >> 6, _ONE << (at & 63).astype(np.uint64))
        low = np.zeros((n * bits + 63) // 64 + 1, np.uint64)
        if bits:
            part = values & np.uint64((1 << bits) - 1)
            where = np.arange(n, dtype=np.int64) * bits
            off = (where & 63).astype(np.uint64)
            _or_into(low, where >> 6, part << off)
            over = np.flatnonzero(off.astype(np.int64) + bits > 64)
            _or_into(low, (where[over] >> 6) + 1, part[over] >> (np.uint64(64) - off[over]))
        count = np.bitwise_count(high).reshape(-1, 8).sum(1, dtype=np.uint64)
        ones = np.concatenate([[np.uint64(0)], np.cumsum(count, dtype=np.uint64)])
        return cls(np.array([n, bits, top], np.int64), high, low, ones)

    def arrays(self) -> list[np.ndarray]:
        return [np.array([self.n, self.bits, self.top], np.int64), self.high, self.low, self.ones]

    def _nth(self, k: np.ndarray, zeros: bool) -> np.ndarray:
        """Position of the k-th (from 0) zero or one of the high bits."""
        before = self.zeros if zeros else self.ones.astype(np.int64)
        block = np.searchsorted(before, k, "right") - 1
        r = (k - before[block]).astype(np.uint16)
        w = self.high.reshape(-1, 8)[block]
        if zeros:
            np.invert(w, out=w)
        upto = np.cumsum(np.bitwise_count(w), axis=1, dtype=np.uint16)
        j = (upto <= r[:, None]).sum(1, dtype=np.uint8)
        rows = np.arange(len(k))
        r -= np.where(j > 0, upto[rows, j - (j > 0)], 0).astype(np.uint16)
        octets = np.ascontiguousarray(w[rows, j]).view(np.uint8).reshape(-1, 8)
        upto = np.cumsum(_BITS[octets], axis=1, dtype=np.uint8)
        r = r.astype(np.uint8)
        o = (upto <= r[:, None]).sum(1, dtype=np.uint8)
        r -= np.where(o > 0, upto[rows, o - (o > 0)], 0).astype(np.uint8)
        return (block * 8 + j) * 64 + o.astype(np.int64) * 8 + _NTH[octets[rows, o], r]

    def _low(self, i: np.ndarray) -> np.ndarray:
        if not self.bits:
            return np.zeros(len(i), np.uint64)
        where = i * self.bits
        word, off = where >> 6, (where & 63).astype(np.uint64)
        v = self.low[word] >> off
        over = off.astype(np.int64) + self.bits > 64
        if over.any():
            v[over] |= self.low[word[over] + 1] << (np.uint64(64) - off[over])
        return v & self.mask

    def get(self, i: np.ndarray) -> np.ndarray:
        """The values at positions i."""
        i = np.asarray(i, np.int64)
        out = np.empty(len(i), np.uint64)
        for a in range(0, len(i), STEP):
            part = i[a : a + STEP]
            out[a : a + STEP] = ((self._nth(part, False) - part).astype(np.uint64) << np.uint64(self.bits)) | self._low(part)
        return out

    def find(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number of values below x, whether x is there), for each x."""
        x = np.asarray(x, np.uint64)
        at, there = np.zeros(len(x), np.int64), np.zeros(len(x), bool)
        if self.n:
            for a in range(0, len(x), STEP):
                at[a : a + STEP], there[a : a + STEP] = self._find(x[a : a + STEP])
        return at, there

    def _find(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = (x >> np.uint64(self.bits)).astype(np.int64)
        out = h > self.top
        h = np.minimum(h, self.top)
        hi = self._nth(h, True) - h
        lo = np.zeros(len(x), np.int64)
        some = np.flatnonzero(h > 0)
        lo[some] = self._nth(h[some] - 1, True) - (h[some] - 1)
        want = x & self.mask
        end = hi.copy()
        act = np.flatnonzero(lo < hi)
        while len(act):
            mid = (lo[act] + hi[act]) >> 1
            less = self._low(mid) < want[act]
            lo[act] = np.where(less, mid + 1, lo[act])
            hi[act] = np.where(less, hi[act], mid)
            act = act[lo[act] < hi[act]]
        lo[out] = self.n
        there = np.zeros(len(x), bool)
        can = np.flatnonzero(~out & (lo < end))
        there[can] = self._low(lo[can]) == want[can]
        return lo, there
