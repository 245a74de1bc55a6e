"""Elias-Fano sequences over flat arrays that can be memory-mapped, with vectorised successor search.

A rising sequence of n numbers below u is split at l = floor(log2(u/n)) bits: the low parts are packed side by side, the
high parts are written in unary, a one for each number and a zero after each value of the high part. Some 2 + l bits a
number. The numbers with one high part lie together; a select over zeros finds where they begin, and a bisection of
their low parts finds one of them.
"""

from __future__ import annotations

import numpy as np

_BLOCK = 8  # words of 64 bits for which one count of zeros is stored


def _set_bits(at: np.ndarray, n_bits: int) -> np.ndarray:
    words = np.zeros(-(-max(1, n_bits) // (64 * _BLOCK)) * _BLOCK, np.uint64)
    np.bitwise_or.at(words, at >> 6, np.uint64(1) << (at & 63).astype(np.uint64))
    return words


def build(keys: np.ndarray) -> dict[str, np.ndarray]:
    """Arrays of the sequence ``keys``: rising, different, unsigned 64-bit."""
    keys = np.asarray(keys, np.uint64)
    n = len(keys)
    top = int(keys[-1]) if n else 0
    low_bits = max(0, (top // max(1, n)).bit_length() - 1)
    high = (keys >> np.uint64(low_bits)).astype(np.int64)
    zeros = (int(high[-1]) if n else 0) + 1
    upper = _set_bits(high + np.arange(n), n + zeros + 1)
    ones = np.bitwise_count(upper).astype(np.int64).reshape(-1, _BLOCK).sum(axis=1)
    before = np.concatenate([[0], np.cumsum(64 * _BLOCK - ones)])
    low = keys & np.uint64((1 << low_bits) - 1)
    words = np.zeros(-(-n * low_bits // 64) + 2, np.uint64)
    if low_bits and n:
        bit = np.arange(n, dtype=np.int64) * low_bits
        word, shift = bit >> 6, (bit & 63).astype(np.uint64)
        np.bitwise_or.at(words, word, low << shift)
        over = np.flatnonzero(shift + np.uint64(low_bits) > 64)
        np.bitwise_or.at(words, word[over] + 1, low[over] >> (np.uint64(64) - shift[over]))
    return {"size": np.array([n, low_bits, zeros], np.int64), "upper": upper, "zeros": before, "low": words}


class Sequence:
    """A built sequence; its arrays may be views of a mapped file."""

    def __init__(self, arrays: dict[str, np.ndarray]):
        self.n, self.low_bits, self.n_zeros = (int(x) for x in arrays["size"])
        self.upper, self.zeros, self.low = arrays["upper"], arrays["zeros"], arrays["low"]
        self.ones = np.arange(len(self.zeros)) * 64 * _BLOCK - self.zeros

    def _select0(self, k: np.ndarray) -> np.ndarray:
        """Position of the k-th zero, counted from 0."""
        block = np.searchsorted(self.zeros, k, side="right") - 1
        left = k - self.zeros[block]
        word = block * _BLOCK
        have = 64 - np.bitwise_count(self.upper[word]).astype(np.int64)
        for _ in range(_BLOCK - 1):
            on = left >= have
            if not on.any():
                break
            left = np.where(on, left - have, left)
            word = word + on
            have = np.where(on, 64 - np.bitwise_count(self.upper[np.minimum(word, len(self.upper) - 1)]).astype(np.int64), have)
        bits, pos = ~self.upper[word], np.zeros(len(k), np.int64)
        for width in (32, 16, 8, 4, 2, 1):
            part = bits & np.uint64((1 << width) - 1)
            c = np.bitwise_count(part).astype(np.int64)
            on = left >= c
            left = np.where(on, left - c, left)
            pos += np.where(on, width, 0)
            bits = np.where(on, bits >> np.uint64(width), part)
        return word * 64 + pos

    def _low_at(self, i: np.ndarray) -> np.ndarray:
        if not self.low_bits:
            return np.zeros(len(i), np.uint64)
        bit = i * self.low_bits
        word, shift = bit >> 6, (bit & 63).astype(np.uint64)
        got = self.low[word] >> shift
        got |= np.where(shift > 0, self.low[word + 1] << ((np.uint64(64) - shift) & np.uint64(63)), np.uint64(0))
        return got & np.uint64((1 << self.low_bits) - 1)

    def _bisect(self, keys: np.ndarray, first: np.ndarray | None = None, stop: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """For each key: the first index not less within its high part and ``first``..``stop``, the end of that range, low
        part, high part known."""
        high = keys >> np.uint64(self.low_bits)
        inside = high < np.uint64(self.n_zeros)
        h = np.where(inside, high, np.uint64(0)).astype(np.int64)
        lo = np.where(h > 0, self._select0(np.maximum(h - 1, 0)) - h + 1, 0)
        end = self._select0(h) - h
        if first is not None:
            lo, end = np.maximum(lo, first), np.minimum(end, stop)
        hi, low = end.copy(), keys & np.uint64((1 << self.low_bits) - 1)
        open_ = np.flatnonzero(lo < hi)
        while len(open_):
            mid = (lo[open_] + hi[open_]) >> 1
            less = self._low_at(mid) < low[open_]
            lo[open_] = np.where(less, mid + 1, lo[open_])
            hi[open_] = np.where(less, hi[open_], mid)
            open_ = open_[lo[open_] < hi[open_]]
        return lo, end, low, inside

    def successor(self, keys: np.ndarray) -> np.ndarray:
        """Index of the first number that is not less than each key; n if there is none."""
        if not self.n:
            return np.zeros(len(keys), np.int64)
        lo, _, _, inside = self._bisect(np.asarray(keys, np.uint64))
        return np.where(inside, lo, self.n)

    def find(self, keys: np.ndarray, first: np.ndarray | None = None, stop: np.ndarray | None = None) -> np.ndarray:
        """Index of each key, -1 where it is not in the sequence, or not between ``first`` and ``stop`` if these are given."""
        if not self.n:
            return np.full(len(keys), -1)
        lo, end, low, inside = self._bisect(np.asarray(keys, np.uint64), first, stop)
        ok = np.flatnonzero(inside & (lo < end))
        ok = ok[self._low_at(lo[ok]) == low[ok]]
        out = np.full(len(keys), -1)
        out[ok] = lo[ok]
        return out

    def access(self, i: np.ndarray) -> np.ndarray:
        """The numbers at ``i``: the i-th one is found by bisection over blocks, then bits."""
        block = np.searchsorted(self.ones, i, side="right") - 1
        left, word = i - self.ones[block], block * _BLOCK
        for _ in range(_BLOCK - 1):
            have = np.bitwise_count(self.upper[word]).astype(np.int64)
            on = left >= have
            if not on.any():
                break
            left, word = np.where(on, left - have, left), word + on
        bits, pos = self.upper[word], np.zeros(len(i), np.int64)
        for width in (32, 16, 8, 4, 2, 1):
            part = bits & np.uint64((1 << width) - 1)
            c = np.bitwise_count(part).astype(np.int64)
            on = left >= c
            left = np.where(on, left - c, left)
            pos += np.where(on, width, 0)
            bits = np.where(on, bits >> np.uint64(width), part)
        return ((word * 64 + pos - i).astype(np.uint64) << np.uint64(self.low_bits)) | self._low_at(i)
