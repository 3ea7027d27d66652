"""A word-level FM-index: suffix order, wavelet tree over the Burrows-Wheeler sequence, sampled suffix positions."""

from __future__ import annotations

import numpy as np


class WaveletTree:
    """Rank over a sequence of symbols: one bit vector per binary digit of the symbol, each a stable split of the one above."""

    def __init__(self, symbols: np.ndarray, bits: int):
        self.bits, self.ones, self.zeros = bits, [], []
        s = symbols.astype(np.int64)
        for level in range(bits - 1, -1, -1):
            bit = (s >> level) & 1
            self.ones.append(np.concatenate(([0], np.cumsum(bit, dtype=np.int64))))
            self.zeros.append(int(len(s) - bit.sum()))
            s = np.concatenate((s[bit == 0], s[bit == 1]))

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol stands before each place."""
        left, right = np.zeros_like(at), at.copy()
        for i, level in enumerate(range(self.bits - 1, -1, -1)):
            one = ((symbol >> level) & 1).astype(bool)
            a, b = self.ones[i][left], self.ones[i][right]
            left = np.where(one, self.zeros[i] + a, left - a)
            right = np.where(one, self.zeros[i] + b, right - b)
        return right - left

    def access(self, at: np.ndarray) -> np.ndarray:
        """The symbol at each place."""
        place, symbol = at.copy(), np.zeros_like(at)
        for i in range(self.bits):
            before = self.ones[i][place]
            bit = self.ones[i][place + 1] - before
            place = np.where(bit == 1, self.zeros[i] + before, place - before)
            symbol = symbol * 2 + bit
        return symbol


class FMIndex:
    """Counts and locates phrases of symbols 1..top in a sequence where 0 separates runs; a phrase never crosses a 0."""

    def __init__(self, text: np.ndarray, top: int, sample: int = 8):
        text = np.concatenate((text.astype(np.int64), [0]))
        n = len(text)
        order = self._suffix_order(text)
        before = text[order - 1]
        self.n, self.sample = n, sample
        self.tree = WaveletTree(before, max(1, int(top).bit_length()))
        counts = np.bincount(text, minlength=top + 2)
        self.first = np.concatenate(([0], np.cumsum(counts)))
        # a separator has no next place in its own run, so its rank isn't followed: every run's first place is sampled too
        start = np.concatenate(([True], text[:-1] == 0))
        kept = (order % sample == 0) | start[order]
        self.marked = np.concatenate(([0], np.cumsum(kept)))
        self.places = order[kept]

    @staticmethod
    def _suffix_order(text: np.ndarray) -> np.ndarray:
        """Order of all suffixes, by prefix doubling; each separator is a symbol of its own, so comparing ends with the run."""
        n = len(text)
        seps = text == 0
        rank = np.where(seps, np.cumsum(seps) - 1, text + int(seps.sum()))
        width = 1
        while True:
            follow = np.zeros(n, dtype=np.int64)
            if width < n:
                follow[: n - width] = rank[width:] + 1
            key = rank * np.int64(2 * n + int(text.max(initial=0)) + 2) + follow
            order = np.argsort(key)
            new = np.concatenate(([0], np.cumsum(np.diff(key[order]) != 0)))
            rank = np.empty(n, dtype=np.int64)
            rank[order] = new
            if new[-1] == n - 1:
                return order
            width *= 2

    def ranges(self, phrases: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Backward search of all phrases at once. phrases: rows of symbols, padded at the right; an unknown symbol is -1."""
        low, high = np.zeros(len(phrases), dtype=np.int64), np.full(len(phrases), self.n, dtype=np.int64)
        for step in range(int(lengths.max(initial=0))):
            at = lengths - 1 - step
            live = np.flatnonzero((at >= 0) & (low < high))
            if not len(live):
                continue
            symbol = phrases[live, at[live]].astype(np.int64)
            lost = symbol <= 0
            symbol = np.where(lost, 0, symbol)
            lo = self.first[symbol] + self.tree.rank(symbol, low[live])
            hi = self.first[symbol] + self.tree.rank(symbol, high[live])
            low[live], high[live] = lo, np.where(lost, lo, hi)
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """The place in the text of each row of the suffix order, by steps back to a sampled one."""
        out, steps = np.empty(len(rows), dtype=np.int64), np.zeros(len(rows), dtype=np.int64)
        row, open_ = rows.astype(np.int64).copy(), np.arange(len(rows))
        while len(open_):
            here = self.marked[row + 1] > self.marked[row]
            done = open_[here]
            out[done] = self.places[self.marked[row[here]]] + steps[done]
            open_, row = open_[~here], row[~here]
            symbol = self.tree.access(row)
            row = self.first[symbol] + self.tree.rank(symbol, row)
            steps[open_] += 1
        return out
