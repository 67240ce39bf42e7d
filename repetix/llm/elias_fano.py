"""Elias-Fano sequences and a level of an n-gram trie on them, in NumPy over a memory map.

A monotone sequence of n numbers below u keeps the low bits of each number as they are, about
log2(u / n) of them, and the high parts in unary: number i sets bit (value >> low) + i. With a
directory of zeros for each 64-bit word, the run of numbers that share a high part is found by
two selections, and a successor search bisects only inside that run. A run of places is decoded
at once, which serves many searches that come in order.
"""

from __future__ import annotations

import mmap
import os
import tempfile

import numpy as np

_ONE = np.uint64(1)


def _kth_bit(words: np.ndarray, k: np.ndarray) -> np.ndarray:
    """Place of the k-th set bit (from 0) of each word."""
    place = np.zeros(len(words), np.uint64)
    k = k.astype(np.int64)
    for width in (32, 16, 8, 4, 2, 1):
        low = words & np.uint64((1 << width) - 1)
        ones = np.bitwise_count(low).astype(np.int64)
        up = k >= ones
        k = np.where(up, k - ones, k)
        place = np.where(up, place + np.uint64(width), place)
        words = np.where(up, words >> np.uint64(width), low)
    return place.astype(np.int64)


class EliasFano:
    """An ascending sequence of non-negative numbers, queried by many values at a time."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, zeros: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.zeros = n, low_bits, low, high, zeros

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        values = values.astype(np.uint64)
        n = len(values)
        top = int(values[-1]) if n else 0
        low_bits = max(0, (top // max(1, n)).bit_length() - 1)
        high_parts = (values >> np.uint64(low_bits)).astype(np.int64)
        at = high_parts + np.arange(n)
        high = np.zeros((int(at[-1]) if n else 0) // 64 + 2, np.uint64)
        np.bitwise_or.at(high, at >> 6, _ONE << (at & 63).astype(np.uint64))
        zeros = np.concatenate(([0], np.cumsum(64 - np.bitwise_count(high).astype(np.int64))))
        low = np.zeros((n * low_bits) // 64 + 2, np.uint64)
        if low_bits:
            kept = values & np.uint64((1 << low_bits) - 1)
            start = np.arange(n, dtype=np.int64) * low_bits
            shift = (start & 63).astype(np.uint64)
            np.bitwise_or.at(low, start >> 6, kept << shift)
            over = (start & 63) + low_bits > 64
            np.bitwise_or.at(low, (start[over] >> 6) + 1, kept[over] >> (np.uint64(64) - shift[over]))
        return cls(n, low_bits, low, high, zeros)

    def _lows(self, i: np.ndarray) -> np.ndarray:
        if not self.low_bits:
            return np.zeros(len(i), np.uint64)
        start = i * self.low_bits
        word, shift = start >> 6, (start & 63).astype(np.uint64)
        high = np.where(shift == 0, np.uint64(0), self.low[word + 1] << ((np.uint64(64) - shift) & np.uint64(63)))
        return (self.low[word] >> shift | high) & np.uint64((1 << self.low_bits) - 1)

    def _before(self, high: np.ndarray) -> np.ndarray:
        """How many numbers have a high part below each of `high`."""
        k = np.maximum(high - 1, 0)
        inside = (high > 0) & (k < self.zeros[-1])
        word = np.searchsorted(self.zeros, np.where(inside, k, 0), side="right") - 1
        place = word * 64 + _kth_bit(~self.high[word], np.where(inside, k, 0) - self.zeros[word])
        return np.where(high <= 0, 0, np.where(inside, np.minimum(place - k, self.n), self.n))

    def find(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of the least number >= x, whether it equals x); index n if there is none."""
        x = x.astype(np.uint64)
        high = (x >> np.uint64(self.low_bits)).astype(np.int64)
        wanted = x & np.uint64((1 << self.low_bits) - 1)
        lo, hi = self._before(high), self._before(high + 1)
        end = hi.copy()
        while (active := lo < hi).any():
            mid = (lo + hi) >> 1
            less = self._lows(np.minimum(mid, max(0, self.n - 1))) < wanted
            hi = np.where(active & ~less, mid, hi)
            lo = np.where(active & less, mid + 1, lo)
        hit = lo < end
        hit[hit] = self._lows(lo[hit]) == wanted[hit]
        return lo, hit

    def access(self, i: np.ndarray) -> np.ndarray:
        """The numbers at these places."""
        ones = 64 * np.arange(len(self.zeros)) - self.zeros
        word = np.searchsorted(ones, i, side="right") - 1
        high = word * 64 + _kth_bit(self.high[word], i - ones[word]) - i
        return (high.astype(np.uint64) << np.uint64(self.low_bits)) | self._lows(i)

    def decode(self, start: int, stop: int) -> np.ndarray:
        """The numbers at places start .. stop - 1, as int64."""
        if start >= stop:
            return np.empty(0, np.int64)
        ones = 64 * np.arange(len(self.zeros)) - self.zeros
        first, last = (int(np.searchsorted(ones, i, side="right")) - 1 for i in (start, stop - 1))
        bits = np.unpackbits(np.ascontiguousarray(self.high[first : last + 1]).view(np.uint8), bitorder="little")
        at = np.flatnonzero(bits)[start - int(ones[first]) : stop - int(ones[first])] + 64 * first
        places = np.arange(start, stop)
        return (at - places) << self.low_bits | self._lows(places).astype(np.int64)

    def arrays(self) -> list[np.ndarray]:
        return [self.low, self.high, self.zeros]


class Quantiser:
    """Logarithms of probabilities in equal steps, in two bytes; code 0 stands for none. A code is off by half a step, under 1.4 per cent, at most."""

    STEP, LEAST = 16 / 1360, -16.0

    @classmethod
    def codes(cls, log10: np.ndarray) -> np.ndarray:
        return (1 + np.rint(np.clip(log10, cls.LEAST, 0) / -cls.STEP)).astype(np.uint16)

    @classmethod
    def probabilities(cls) -> np.ndarray:
        return np.concatenate(([0.0], 10 ** (np.arange(1361) * -cls.STEP)))


class TrieLevel:
    """The successors of numbered contexts: monotone pointers, successors relative to their context, quantised probabilities and counts.

    The successors of context j stand at places pointers[j] to pointers[j + 1]. A list begins
    just above the last number of the list before, so all lists make one ascending sequence of
    a small universe, and a word's number is known only from its context's pointer.
    """

    AT_ONCE = 1 << 18

    def __init__(self, n_contexts: int, contexts: np.ndarray, words: np.ndarray, log10: np.ndarray, totals: np.ndarray):
        """Parallel arrays sorted by (context, word), without repeats; contexts and words are numbered from 0."""
        first = np.searchsorted(contexts, np.arange(n_contexts + 1))
        widths = np.where(first[1:] > first[:-1], words[np.maximum(first[1:] - 1, 0)] + 1 if len(words) else 0, 0)
        bases = np.concatenate(([0], np.cumsum(widths)))
        self.pointers, self.successors = EliasFano.of(first), EliasFano.of(bases[contexts] + words)
        self.codes, self.totals = Quantiser.codes(log10), totals.astype(np.uint32 if totals.max(initial=0) < 1 << 32 else np.uint64)

    def map_to_file(self) -> TrieLevel:
        """Move the level to a memory-mapped file that has no name any more, so nothing is left behind."""
        levels = (self.pointers, self.successors)
        arrays = [a for level in levels for a in level.arrays()] + [self.codes, self.totals]
        handle, path = tempfile.mkstemp(prefix="trie-")
        try:
            offsets = []
            with os.fdopen(handle, "r+b") as f:
                for a in arrays:
                    f.seek(-f.tell() % 8, os.SEEK_CUR)
                    offsets.append(f.tell())
                    f.write(a.tobytes())
                f.write(b"\0" * 8)
                f.flush()
                view = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        finally:
            os.unlink(path)
        mapped = [np.frombuffer(view, a.dtype, len(a), at) for a, at in zip(arrays, offsets, strict=True)]
        for n, level in enumerate(levels):
            level.low, level.high, level.zeros = mapped[3 * n : 3 * n + 3]
        self.codes, self.totals = mapped[6:]
        return self

    def places(self, contexts: np.ndarray, words: np.ndarray) -> np.ndarray:
        """The place of each (context, word), -1 where the trie lacks it; the questions ascend by context."""
        out = np.full(len(contexts), -1, np.int64)
        for at in range(0, len(contexts), self.AT_ONCE):
            j, w = contexts[at : at + self.AT_ONCE], words[at : at + self.AT_ONCE]
            pointers = self.pointers.decode(int(j[0]), int(j[-1]) + 2)
            lo, hi = pointers[j - j[0]], pointers[j - j[0] + 1]
            start = max(0, int(lo[0]) - 1)
            numbers = self.successors.decode(start, int(hi[-1]))
            if not len(numbers):
                continue
            base = np.where(lo > 0, numbers[np.maximum(lo - 1 - start, 0)] + 1, 0)
            found = np.searchsorted(numbers, base + w)  # no number below the context's list is as large
            inside = np.flatnonzero(found + start < hi)
            inside = inside[numbers[found[inside]] == (base + w)[inside]]
            out[at + inside] = found[inside] + start
        return out

    def successors_of(self, context: int) -> tuple[np.ndarray, np.ndarray]:
        """(words, codes) of one context's list, from its pointers."""
        lo, hi = self.pointers.decode(context, context + 2).tolist()
        numbers = self.successors.decode(max(0, lo - 1), hi)
        base, numbers = (int(numbers[0]) + 1, numbers[1:]) if lo else (0, numbers)
        return numbers - base, np.asarray(self.codes[lo:hi])
