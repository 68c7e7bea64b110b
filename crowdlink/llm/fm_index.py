"""Full-text index of a shard of numbered words: suffix order, wavelet matrix, sampled positions."""

from __future__ import annotations

import numpy as np


class Bits:
    """Bit row with constant-time rank: 64-bit words and the ones before each."""

    def __init__(self, bits: np.ndarray):
        packed = np.packbits(bits, bitorder="little")
        words = np.zeros((len(bits) >> 6) + 1, np.uint64)
        words.view(np.uint8)[: packed.size] = packed
        self.words = words
        self.before = np.zeros(words.size, np.int64)
        np.cumsum(np.bitwise_count(words[:-1]), out=self.before[1:])

    def get(self, i: np.ndarray) -> np.ndarray:
        return (self.words[i >> 6] >> (i & 63).astype(np.uint64)) & np.uint64(1) != 0

    def rank(self, i: np.ndarray) -> np.ndarray:
        """Ones before place ``i``."""
        low = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[i >> 6] + np.bitwise_count(self.words[i >> 6] & low)


class WaveletMatrix:
    """Rank of any symbol in a sequence, by one bit row for each bit of the symbols."""

    def __init__(self, symbols: np.ndarray, top: int):
        self.levels, now = [], symbols
        for level in range(max(1, int(top).bit_length()) - 1, -1, -1):
            bits = (now >> level) & 1 == 1
            row = Bits(bits)
            self.levels.append((level, row, len(now) - int(bits.sum())))
            now = np.concatenate([now[~bits], now[bits]])
        every = np.arange(top + 1)
        self.origin = self._descend(every, np.zeros(top + 1, np.int64))

    def _descend(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        for level, row, zeros in self.levels:
            ones = row.rank(i)
            i = np.where((symbol >> level) & 1 == 1, zeros + ones, i - ones)
        return i

    def rank(self, symbol: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Occurrences of ``symbol`` before place ``i``."""
        return self._descend(symbol, i) - self.origin[symbol]

    def access(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at place ``i`` and its rank there."""
        symbol = np.zeros(len(i), np.int64)
        for level, row, zeros in self.levels:
            bit, ones = row.get(i), row.rank(i)
            symbol |= bit.astype(np.int64) << level
            i = np.where(bit, zeros + ones, i - ones)
        return symbol, i - self.origin[symbol]


def suffix_order(text: np.ndarray, top: int) -> np.ndarray:
    """Places of ``text`` in the order of their suffixes, each read up to its first 0; equal ones by place.

    Sorts by the first few symbols, then doubles the length for the groups that are still undecided.
    """
    n = len(text)
    stops = np.flatnonzero(text == 0)
    left = stops[np.searchsorted(stops, np.arange(n))] - np.arange(n)
    width = max(1, int(top).bit_length())
    h = max(1, 63 // width)
    key = np.zeros(n, np.int64)
    for k in range(h):
        here = left >= k
        key <<= width
        key[here] |= text[np.flatnonzero(here) + k]
    order = np.argsort(key, kind="stable")
    key = key[order]
    head = np.ones(n, bool)
    head[1:] = key[1:] != key[:-1]
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    while True:
        alone = head.copy()
        alone[:-1] &= head[1:]
        slots = np.flatnonzero(~alone & (left[order] >= h))
        if not slots.size:
            return order
        p = order[slots]
        both = rank[p] * (n + 1) + rank[p + h]
        turn = np.argsort(both, kind="stable")
        p, both = p[turn], both[turn]
        order[slots] = p
        fresh = np.ones(len(p), bool)
        fresh[1:] = both[1:] != both[:-1]
        head[slots] = fresh
        rank[p] = np.maximum.accumulate(np.where(fresh, slots, 0))
        h *= 2


class FmIndex:
    """Backward search over ``text``: runs of symbols 1..top, each run closed by a 0."""

    def __init__(self, text: np.ndarray, top: int, every: int = 16):
        order = suffix_order(text, top)
        self.last = WaveletMatrix(text[order - 1], top)
        self.below = np.zeros(top + 2, np.int64)
        np.cumsum(np.bincount(text, minlength=top + 1), out=self.below[1:])
        opens = np.ones(len(text), bool)
        opens[1:] = text[:-1] == 0
        kept = (order % every == 0) | opens[order]
        self.marked, self.places = Bits(kept), order[kept]

    def search(self, patterns: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row interval of each pattern (a row of ``patterns``, its symbols at the left)."""
        place = lengths - 1
        symbol = patterns[np.arange(len(patterns)), place].astype(np.int64)
        low, high = self.below[symbol].copy(), self.below[symbol + 1].copy()
        alive = np.flatnonzero((place > 0) & (high > low))
        while alive.size:
            place[alive] -= 1
            symbol = patterns[alive, place[alive]].astype(np.int64)
            low[alive] = self.below[symbol] + self.last.rank(symbol, low[alive])
            high[alive] = self.below[symbol] + self.last.rank(symbol, high[alive])
            alive = alive[(place[alive] > 0) & (high[alive] > low[alive])]
        return low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text place of each row: step back to a sampled one and count the steps."""
        out, at, open_, steps = np.zeros(len(rows), np.int64), rows.copy(), np.arange(len(rows)), 0
        while open_.size:
            found = self.marked.get(at)
            out[open_[found]] = self.places[self.marked.rank(at[found])] + steps
            open_, at = open_[~found], at[~found]
            if open_.size:
                symbol, rank = self.last.access(at)
                at = self.below[symbol] + rank
            steps += 1
        return out
