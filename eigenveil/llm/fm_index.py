"""A compressed full-text index over integer sequences: wavelet matrix and backward search.

Suffixes are ordered to a bounded depth, which is all that patterns up to that depth
need: the bounds of a pattern's interval do not depend on how ties beyond it fall.  The
index keeps the wavelet matrix of the Burrows-Wheeler transform and one 32-bit value per
suffix; neither the text nor the suffix array stays.
"""

from __future__ import annotations

import numpy as np


class WaveletMatrix:
    """Bit rows of a symbol sequence, packed to 64-bit words with counts before each word."""

    def __init__(self, symbols: np.ndarray, alphabet: int):
        self.levels = max(1, int(alphabet - 1).bit_length())
        self.bits: list[np.ndarray] = []
        self.before: list[np.ndarray] = []
        self.zeros: list[int] = []
        now = symbols
        for level in reversed(range(self.levels)):
            row = ((now >> level) & 1).astype(bool)
            packed = np.packbits(row, bitorder="little")
            words = np.zeros(len(row) // 64 + 1, np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            self.bits.append(words)
            self.before.append(np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int32)[:-1]]).astype(np.int32))
            self.zeros.append(int(len(row) - row.sum()))
            now = np.concatenate([now[~row], now[row]])
        self.start = self._descend(np.arange(alphabet), np.zeros(alphabet, np.int64))

    def _descend(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        for k in range(self.levels):
            word = at >> 6
            ones = self.before[k][word] + np.bitwise_count(self.bits[k][word] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))
            at = np.where((symbols >> (self.levels - 1 - k)) & 1, self.zeros[k] + ones, at - ones)
        return at

    def rank(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol stands before its position."""
        return self._descend(symbols, at) - self.start[symbols]


def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Starts of all suffixes, ordered by their first ``depth`` symbols at least (prefix doubling)."""
    n = len(text)
    rank, width = text.astype(np.int64), 1
    while width < depth and n:
        after = np.zeros(n, np.int64)
        after[: max(0, n - width)] = rank[width:] + 1
        keys = rank * (int(rank.max()) + 2) + after
        order = np.argsort(keys)
        ordered = keys[order]
        fresh = np.cumsum(np.append(False, ordered[1:] != ordered[:-1]))
        rank[order] = fresh
        width *= 2
        if fresh[-1] == n - 1:
            break
    return np.argsort(rank)


class FmIndex:
    """Index of ``text`` (integers from 0; 0 separates sequences) with a value at each position, for patterns up to ``depth``."""

    def __init__(self, text: np.ndarray, values: np.ndarray, depth: int):
        order = suffix_order(text, depth + 1)
        self.size = len(text)
        self.alphabet = int(text.max()) + 1 if len(text) else 1
        self.counts = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=self.alphabet))])
        self.values = values[order].astype(np.int32)
        self.wavelet = WaveletMatrix(text[order - 1], self.alphabet)

    def least_in(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """The least value of each interval of suffixes; intervals must not be empty."""
        if not len(lo):
            return np.empty(0, np.int32)
        n = self.size + 1
        at, back = np.unique(lo * n + hi, return_inverse=True)
        ordered = np.append(self.values, np.int32(0))
        return np.minimum.reduceat(ordered, np.stack([at // n, at % n], 1).ravel())[::2][back]

    def matching_statistics(self, stream: np.ndarray, ends: np.ndarray, longest: int) -> tuple[np.ndarray, np.ndarray]:
        """For each end in ``stream``: the length of the longest match that ends there, up to ``longest``,
        and the least value among its occurrences.

        Backward search of all ends side by side, one symbol further to the left in each
        step; an end whose match breaks off keeps the interval it had.  The symbol 0 and
        symbols that the index lacks match nothing.
        """
        matched = np.zeros(len(ends), np.int64)
        lo, hi = np.zeros(len(ends), np.int64), np.full(len(ends), self.size, np.int64)
        alive = np.flatnonzero(ends > 0)
        for j in range(1, longest + 1):
            alive = alive[ends[alive] >= j]
            c = stream[ends[alive] - j].astype(np.int64)
            known = (c > 0) & (c < self.alphabet)
            alive, c = alive[known], c[known]
            if j == 1:
                a, b = self.counts[c], self.counts[c + 1]
            else:
                both = self.wavelet.rank(np.concatenate([c, c]), np.concatenate([lo[alive], hi[alive]])) + np.tile(self.counts[c], 2)
                a, b = both[: len(c)], both[len(c) :]
            found = a < b
            alive = alive[found]
            lo[alive], hi[alive] = a[found], b[found]
            matched[alive] += 1
        out = np.full(len(ends), np.iinfo(np.int32).max, np.int32)
        some = np.flatnonzero(matched > 0)
        out[some] = self.least_in(lo[some], hi[some])
        return matched, out
