"""A compressed FM-index over integer sequences: wavelet matrix of the Burrows-Wheeler transform, all queries at once."""

from __future__ import annotations

import numpy as np


class Wavelet:
    """Bits of each level packed into words, with a running count per word; ranks for many positions at once."""

    def __init__(self, seq: np.ndarray, symbols: int):
        self.n = len(seq)
        self.levels = max(1, int(symbols - 1).bit_length())
        self.words, self.ones, self.zeros = [], [], []
        for level in range(self.levels - 1, -1, -1):
            bit = ((seq >> level) & 1).astype(bool)
            pad = np.zeros((self.n // 64 + 1) * 64, bool)
            pad[: self.n] = bit
            w = np.packbits(pad, bitorder="little").view(np.uint64)
            self.words.append(w)
            self.ones.append(np.concatenate([[0], np.cumsum(np.bitwise_count(w))]).astype(np.int32))
            self.zeros.append(self.n - int(bit.sum()))
            seq = np.concatenate([seq[~bit], seq[bit]])

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Position of (symbol, occurrence count before ``at``) in the last level's order."""
        at = at.astype(np.int64)
        for k in range(self.levels):
            bit = ((symbol >> (self.levels - 1 - k)) & 1).astype(bool)
            w = at >> 6
            ones = self.ones[k][w] + np.bitwise_count(self.words[k][w] & ((np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)))
            at = np.where(bit, self.zeros[k] + ones, at - ones)
        return at


class FMIndex:
    """Index of ``seq``, symbols 0 .. symbols - 1; 0 separates texts and never takes part in a pattern. Suffixes are sorted by
    their first ``depth`` symbols, which is enough for patterns of that length."""

    def __init__(self, seq: np.ndarray, symbols: int, depth: int):
        n = len(seq)
        self.sa = self._sort(seq.astype(np.int64), n, depth)
        bwt = seq[self.sa - 1]  # the text is taken as a circle; position 0 follows the last separator
        self.tree = Wavelet(bwt, symbols)
        count = np.bincount(seq, minlength=symbols)
        self.first = np.concatenate([[0], np.cumsum(count)[:-1]]).astype(np.int64)
        self.start = self.tree.rank(np.arange(symbols), np.zeros(symbols, np.int64))
        self.n = n

    @staticmethod
    def _sort(rank: np.ndarray, n: int, depth: int) -> np.ndarray:
        """Ranks of three neighbours (two, where three do not fit into 63 bits) make the next rank, until all are deep enough."""
        step = 1
        while True:
            bits = max(1, int(rank.max()).bit_length()) if n else 1
            few = 3 if 3 * bits <= 63 else 2
            key = rank << ((few - 1) * bits)
            for k in range(1, few):
                key[: max(0, n - k * step)] |= rank[k * step :] << ((few - 1 - k) * bits)
            order = np.argsort(key, kind="stable")
            step *= few
            if step >= depth:
                return order
            s = key[order]
            rank = np.empty(n, np.int64)
            rank[order] = np.concatenate([[0], np.cumsum(s[1:] != s[:-1])])

    def extend(self, symbol: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Intervals of the patterns with one more symbol in front."""
        base = self.first[symbol] - self.start[symbol]
        return base + self.tree.rank(symbol, lo), base + self.tree.rank(symbol, hi)
