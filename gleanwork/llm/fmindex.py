"""FM-index over word symbols, in numpy: suffix order, wavelet ranks, backward search, sampled suffix positions.

Symbol 0 ends a run of words; every 0 counts as a symbol of its own, so a suffix is compared only up to the end of its run.
"""

from __future__ import annotations

import numpy as np


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """Suffix array by prefix doubling; only suffixes still tied are sorted again."""
    n = len(symbols)
    ends = symbols == 0
    n_ends = int(ends.sum())
    rank = symbols.astype(np.int64) + n_ends
    rank[ends] = np.arange(n_ends)
    order = np.argsort(rank, kind="stable")
    sorted_rank = rank[order]
    first = np.flatnonzero(np.r_[True, sorted_rank[1:] != sorted_rank[:-1]])
    group = np.repeat(first, np.diff(np.r_[first, n]))
    rank = np.empty(n, np.int64)
    rank[order] = group
    tied = np.flatnonzero(np.repeat(np.diff(np.r_[first, n]) > 1, np.diff(np.r_[first, n])))
    step = 1
    while len(tied):
        rows = order[tied]
        ahead = np.where(rows + step < n, rank[np.minimum(rows + step, n - 1)], -1)
        key = rank[rows] * (n + 1) + ahead + 1
        again = np.argsort(key, kind="stable")
        rows, key = rows[again], key[again]
        order[tied] = rows
        starts = np.r_[True, key[1:] != key[:-1]]
        at = np.flatnonzero(starts)
        rank_of = np.repeat(tied[at], np.diff(np.r_[at, len(tied)]))
        rank[rows] = rank_of
        tied = tied[np.repeat(np.diff(np.r_[at, len(tied)]) > 1, np.diff(np.r_[at, len(tied)]))]
        step *= 2
    return order


class Wavelet:
    """Wavelet matrix: one packed bit row for each bit of the symbols, with counts of ones before each 64-bit word."""

    def __init__(self, values: np.ndarray, top: int):
        self.n, self.depth = len(values), max(1, int(top).bit_length())
        self.rows, cur = [], values.astype(np.uint32)
        for level in range(self.depth - 1, -1, -1):
            bit = ((cur >> np.uint32(level)) & np.uint32(1)).astype(np.uint8)
            packed = np.packbits(bit, bitorder="little")
            words = np.zeros(len(packed) // 8 + 2, np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            ones = np.r_[0, np.cumsum(np.bitwise_count(words), dtype=np.int64)]
            zeros = self.n - int(bit.sum())
            self.rows.append((level, words, ones, zeros))
            cur = np.concatenate([cur[bit == 0], cur[bit == 1]])

    @staticmethod
    def _ones(words: np.ndarray, ones: np.ndarray, at: np.ndarray) -> np.ndarray:
        w = at >> 6
        mask = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return ones[w] + np.bitwise_count(words[w] & mask)

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often symbol stands before position at, elementwise."""
        lo, hi = np.zeros_like(at), at
        for level, words, ones, zeros in self.rows:
            one = (symbol >> level) & 1 == 1
            a, b = self._ones(words, ones, lo), self._ones(words, ones, hi)
            lo, hi = np.where(one, zeros + a, lo - a), np.where(one, zeros + b, hi - b)
        return hi - lo

    def at(self, row: np.ndarray) -> np.ndarray:
        """The symbols at rows."""
        out = np.zeros_like(row)
        for level, words, ones, zeros in self.rows:
            one = ((words[row >> 6] >> (row & 63).astype(np.uint64)) & np.uint64(1)) == 1
            a = self._ones(words, ones, row)
            out |= one.astype(np.int64) << level
            row = np.where(one, zeros + a, row - a)
        return out


class FMIndex:
    def __init__(self, symbols: np.ndarray, every: int = 16):
        """symbols: int array of runs, each ended by a 0; every: one position in so many keeps its place."""
        n = len(symbols)
        order = suffix_order(symbols)
        before = symbols[order - 1]  # the row of position 0 wraps around to the last 0
        top = int(symbols.max(initial=0))
        self.n, self.wavelet = n, Wavelet(before, top)
        self.first = np.r_[0, np.cumsum(np.bincount(symbols, minlength=top + 1))].astype(np.int64)
        kept = (order % every == 0) | (before == 0)  # walks back never leave a run
        self.kept = np.zeros(n + 1, np.int64)
        np.cumsum(kept, out=self.kept[1:])
        self.places = order[kept]

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row ranges of equally long patterns (rows of a matrix), by backward search; empty where lo == hi."""
        lo, hi = np.zeros(len(patterns), np.int64), np.full(len(patterns), self.n, np.int64)
        live = np.flatnonzero((patterns < len(self.first) - 1).all(axis=1))
        hi[np.setdiff1d(np.arange(len(patterns)), live, assume_unique=True)] = 0
        for j in range(patterns.shape[1] - 1, -1, -1):
            c = patterns[live, j]
            a = self.first[c] + self.wavelet.rank(c, lo[live])
            b = self.first[c] + self.wavelet.rank(c, hi[live])
            lo[live], hi[live] = a, b
            live = live[a < b]
            if not len(live):
                break
        hi = np.maximum(lo, hi)
        return lo, hi

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of rows: walk back to the nearest kept position."""
        out, steps, at, left = np.empty(len(rows), np.int64), np.zeros(len(rows), np.int64), rows.copy(), np.arange(len(rows))
        while len(left):
            row = at[left]
            done = self.kept[row + 1] > self.kept[row]
            out[left[done]] = self.places[self.kept[row[done]]] + steps[left[done]]
            left, row = left[~done], row[~done]
            if len(left):
                c = self.wavelet.at(row)
                at[left] = self.first[c] + self.wavelet.rank(c, row)
                steps[left] += 1
        return out
