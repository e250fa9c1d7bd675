"""FM-index over a sequence of integer symbols: suffix sorting, wavelet matrix, count and locate."""

from __future__ import annotations

import numpy as np


def suffix_order(s: np.ndarray) -> np.ndarray:
    """Suffix array of s (positive symbols). Ranks over growing prefixes; only suffixes still tied are sorted again."""
    n = len(s)
    rank = s.astype(np.int64)
    order, slots, reach = np.arange(n), np.arange(n), 1
    while len(slots):
        bits = max(int(rank.max()).bit_length(), 1)
        steps = 3 if 3 * bits <= 63 else 2
        tied = order[slots]
        key = rank[tied]
        for k in range(1, steps):
            at = tied + k * reach
            key = (key << bits) | np.where(at < n, rank[np.minimum(at, n - 1)], 0)
        by = np.argsort(key, kind="stable")
        tied, key = tied[by], key[by]
        order[slots] = tied
        fresh = np.concatenate([[True], key[1:] != key[:-1]])
        first = np.maximum.accumulate(np.where(fresh, slots, 0))
        if reach == 1:
            rank = np.empty(n, np.int64)
        rank[tied] = first + 1
        single = fresh & np.concatenate([fresh[1:], [True]])
        slots, reach = slots[~single], reach * steps
    return order


class WaveletMatrix:
    """Rank and access over a sequence by one bit vector a level."""

    def __init__(self, seq: np.ndarray):
        self.levels = max(int(seq.max(initial=0)).bit_length(), 1)
        self.words, self.ranks, self.zeros = [], [], []
        for level in range(self.levels - 1, -1, -1):
            bit = ((seq >> level) & 1).astype(bool)
            packed = np.zeros((len(seq) // 64 + 1) * 8, np.uint8)
            got = np.packbits(bit, bitorder="little")
            packed[: len(got)] = got
            words = packed.view("<u8")
            self.words.append(words)
            self.ranks.append(np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)]))
            seq = np.concatenate([seq[~bit], seq[bit]])
            self.zeros.append(len(seq) - int(self.ranks[-1][-1]))

    def _ones(self, k: int, at: np.ndarray) -> np.ndarray:
        low = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.ranks[k][at >> 6] + np.bitwise_count(self.words[k][at >> 6] & low).astype(np.int64)

    def descend(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Where position ``at`` falls in the last level along the bits of each symbol."""
        for k in range(self.levels):
            ones = self._ones(k, at)
            at = np.where((symbols >> (self.levels - 1 - k)) & 1, self.zeros[k] + ones, at - ones)
        return at

    def access(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbols at these positions and where they fall in the last level."""
        symbols = np.zeros(len(at), np.int64)
        for k in range(self.levels):
            bit = (self.words[k][at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)
            ones = self._ones(k, at)
            at = np.where(bit, self.zeros[k] + ones, at - ones)
            symbols = (symbols << 1) | bit.astype(np.int64)
        return symbols, at


class FMIndex:
    """Backward search over s (symbols from 1 on; 0 is kept for the end), occurrences by sampled suffix positions."""

    EVERY = 16

    def __init__(self, s: np.ndarray):
        text = np.concatenate([s, [0]])
        order = suffix_order(text + 1)
        self.size = len(text)
        self.tree = WaveletMatrix(text[order - 1])
        self.below = np.concatenate([[0], np.cumsum(np.bincount(text))])
        kept = order % self.EVERY == 0
        packed = np.zeros((len(text) // 64 + 1) * 8, np.uint8)
        got = np.packbits(kept, bitorder="little")
        packed[: len(got)] = got
        self.kept, self.places = packed.view("<u8"), order[kept]
        self.kept_ranks = np.concatenate([[0], np.cumsum(np.bitwise_count(self.kept), dtype=np.int64)])
        self.starts: dict[int, int] = {}

    def _start(self, symbols: np.ndarray) -> np.ndarray:
        distinct, back = np.unique(symbols, return_inverse=True)
        return self.tree.descend(distinct, np.zeros(len(distinct), np.int64))[back]

    def search(self, phrases: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """phrases: a row of symbols each. Gives the rows that occur and their ranges of suffixes."""
        which = np.arange(len(phrases))
        low, high = np.zeros(len(phrases), np.int64), np.full(len(phrases), self.size, np.int64)
        for column in range(phrases.shape[1] - 1, -1, -1):
            if not len(which):
                break
            c = phrases[which, column]
            shift = self.below[c] - self._start(c)
            low, high = self.tree.descend(c, low) + shift, self.tree.descend(c, high) + shift
            found = low < high
            which, low, high = which[found], low[found], high[found]
        return which, low, high

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of these suffixes: step back to the next sampled one."""
        out, open_, steps = np.zeros(len(rows), np.int64), np.arange(len(rows)), 0
        while len(open_):
            word, bit = self.kept[rows >> 6], (rows & 63).astype(np.uint64)
            hit = ((word >> bit) & np.uint64(1)).astype(bool)
            rank = self.kept_ranks[rows[hit] >> 6] + np.bitwise_count(word[hit] & ((np.uint64(1) << bit[hit]) - np.uint64(1)))
            out[open_[hit]] = self.places[rank] + steps
            open_, rows = open_[~hit], rows[~hit]
            if len(open_):
                symbols, at = self.tree.access(rows)
                rows = self.below[symbols] + at - self._start(symbols)
            steps += 1
        return out
