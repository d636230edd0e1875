"""An FM-index over integer sequences: suffix array, BWT, wavelet matrix with packed bits, backward search of many lanes."""

from __future__ import annotations

import numpy as np


def suffix_array(seq: np.ndarray, depth: int) -> np.ndarray:
    """Places of all suffixes, ordered by their first `depth` symbols at least."""
    _, rank = np.unique(seq, return_inverse=True)
    order, h, n = np.argsort(rank), 1, len(seq)
    while h < depth and n:
        second = np.zeros(n, np.int64)
        second[: n - h] = rank[h:] + 1
        key = rank.astype(np.int64) * (n + 2) + second
        order = np.argsort(key)
        key = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.concatenate([[0], np.cumsum(key[1:] != key[:-1])])
        if rank[order[-1]] == n - 1:
            break
        h *= 2
    return order


class Bits:
    """A bit vector in 64-bit words with a count before every word: 1.5 bits a bit, rank in constant time."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        packed = np.packbits(np.concatenate([bits, np.zeros(-n % 64 + 64, bool)]), bitorder="little")
        self.words = packed.view(np.uint64)
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words[:-1]))]).astype(np.int32)
        self.zeros = n - int(bits.sum())

    def rank1(self, i: np.ndarray) -> np.ndarray:
        w = i >> 6
        mask = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[w] + np.bitwise_count(self.words[w] & mask)


class WaveletMatrix:
    def __init__(self, seq: np.ndarray, n_symbols: int):
        self.shifts = list(range(max(int(n_symbols - 1).bit_length(), 1) - 1, -1, -1))
        self.levels = []
        for s in self.shifts:
            bit = (seq >> s & 1).astype(bool)
            self.levels.append(Bits(bit))
            seq = np.concatenate([seq[~bit], seq[bit]])
        self.first = self._down(np.arange(n_symbols), np.zeros(n_symbols, np.int64))

    def _down(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        for s, level in zip(self.shifts, self.levels):
            ones = level.rank1(i)
            i = np.where(symbol >> s & 1, level.zeros + ones, i - ones)
        return i

    def rank(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How often each symbol stands before place i."""
        return self._down(symbol, i) - self.first[symbol]


class FMIndex:
    """Index of segments (their symbols in a row, and their lengths), each with the number of places in the corpus where it stands.

    Symbol 0 parts the segments. A pattern's weight is the number of corpus places of its occurrences.
    """

    def __init__(self, symbols: np.ndarray, lengths: np.ndarray, weights: np.ndarray, n_symbols: int, depth: int):
        seq = np.zeros(int(lengths.sum() + len(lengths) + 1), np.int64)
        self.starts = np.cumsum(lengths + 1) - lengths
        seq[np.arange(len(symbols)) + np.repeat(np.arange(len(lengths)) + 1, lengths)] = symbols
        order = suffix_array(seq, depth)
        self.seq, self.lengths = seq, lengths
        self.tree = WaveletMatrix(seq[order - 1], n_symbols)
        counts = np.bincount(seq, minlength=n_symbols)
        self.before = np.cumsum(counts) - counts
        each = np.repeat(np.concatenate([[0], weights]), np.concatenate([[1], lengths + 1]))
        self.weight = np.concatenate([[0], np.cumsum(each[order])])

    def match_lengths(self, ends: np.ndarray, limits: np.ndarray, least: int = 2) -> np.ndarray:
        """Matching statistics: for each place just behind a symbol of the indexed text, the most symbols (up to the
        limit) before it that stand in `least` corpus places or more; by backward search of all lanes at a time."""
        n = len(ends)
        length = np.zeros(n, np.int64)
        lane, lo, hi = np.arange(n), np.zeros(n, np.int64), np.full(n, len(self.seq), np.int64)
        while len(lane):
            symbol = self.seq[ends[lane] - 1 - length[lane]]
            both = self.tree.rank(np.concatenate([symbol, symbol]), np.concatenate([lo, hi]))
            lo, hi = self.before[symbol] + both[: len(lane)], self.before[symbol] + both[len(lane) :]
            on = self.weight[hi] - self.weight[lo] >= least
            length[lane[on]] += 1
            go = on & (length[lane] < limits[lane])
            lane, lo, hi = lane[go], lo[go], hi[go]
        return length
