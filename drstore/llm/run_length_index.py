"""A run-length index over short strings in an order, and matching statistics of each against the earlier ones.

The strings (rows of a padded matrix) are indexed together: suffixes are sorted by prefix doubling (equal suffixes by the order of their strings),
the Burrows-Wheeler transform of that order is stored by runs of equal symbols, and a suffix-array sample at both ends of each run
names a string and place. A step to the preceding character is one search among run starts and one addition. Rows are also cut where
neighbours share less than ``reach`` characters; each such group keeps the least owner of its strings, so a string that is
walked backwards through the index learns at each place whether ``reach`` characters from there also occur with a smaller owner.
"""

from __future__ import annotations

import numpy as np

PACK = 5  # symbols of 9 bits in the first key


class RunLengthIndex:
    def __init__(self, symbols: np.ndarray, length: np.ndarray, owner: np.ndarray, reach: int):
        """symbols: (strings, width) of 1..256, 0 beyond the string's length. Strings are in ascending order of owner."""
        if reach < PACK:
            raise ValueError(f"strings shorter than {PACK} are not indexed")
        m, width = symbols.shape
        self.m, self.width, self.length, self.reach = m, width, length, reach
        real = np.arange(width + 1)[None, :] <= length[:, None]  # one empty suffix for each string
        padded = np.zeros((m, width + PACK), np.uint64)
        padded[:, :width] = symbols
        key = np.zeros((m, width + 1), np.uint64)
        for k in range(PACK):
            key = key << np.uint64(9) | padded[:, k : k + width + 1]
        flat = np.flatnonzero(real.ravel())
        rank, order = self._ranks(key.ravel(), flat, 9 * PACK)
        depth, levels = PACK, [(PACK, rank)]
        bits = max(1, int(len(key.ravel())).bit_length())
        while depth < max(width, reach):
            ahead = np.zeros((m, width + 1), np.uint64)
            if depth <= width:
                ahead[:, : width + 1 - depth] = rank.reshape(m, width + 1)[:, depth:]
            rank, order = self._ranks(rank << np.uint64(bits) | ahead.ravel(), flat, 2 * bits)
            depth *= 2
            if depth <= reach:
                levels.append((depth, rank))
        self.suffix = order  # flattened (string, column) by rank
        string, column = order // (width + 1), order % (width + 1)
        before = np.where(column > 0, symbols[string, np.maximum(column - 1, 0)], 0)
        # runs
        head = np.ones(len(order), bool)
        head[1:] = before[1:] != before[:-1]
        self.run_start = np.flatnonzero(head)
        self.run_symbol = before[self.run_start]
        run_length = np.diff(np.append(self.run_start, len(order)))
        counts = np.bincount(self.run_symbol.astype(np.int64), run_length, minlength=257).astype(np.int64)
        begins = np.concatenate([[0], np.cumsum(counts)])[:-1]
        # suffixes that begin with a symbol come after all empty suffixes and smaller symbols; the transform has as many 0s as strings
        by_symbol = np.argsort(self.run_symbol, kind="stable")
        before_run = np.empty(len(run_length), np.int64)
        taken = np.cumsum(run_length[by_symbol]) - run_length[by_symbol]
        before_run[by_symbol] = taken - begins[self.run_symbol[by_symbol].astype(np.int64)]
        self.run_shift = begins[self.run_symbol.astype(np.int64)] + before_run - self.run_start
        self.sample_first, self.sample_last = order[self.run_start], order[np.append(self.run_start[1:], len(order)) - 1]
        # groups of rows that share ``reach`` characters
        level, r = levels[-1]
        full = length[string] - column >= reach
        second = np.where(column + reach - level <= width, order + reach - level, 0)
        same = np.zeros(len(order), bool)
        same[1:] = full[1:] & full[:-1] & (r[order[1:]] == r[order[:-1]]) & (r[second[1:]] == r[second[:-1]])
        start = np.flatnonzero(~same)
        self.group_of_row = np.cumsum(~same) - 1
        self.group_owner = np.minimum.reduceat(owner[string], start) if len(start) else np.empty(0, owner.dtype)

    @staticmethod
    def _ranks(key: np.ndarray, flat: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
        """Ranks (from 1; 0 elsewhere) of the entries ``flat`` of a key of so many bits, and those entries by key, equal ones as in ``flat``."""
        low = max(1, len(flat).bit_length())
        if bits + low <= 64:  # place and key are sorted as one number
            k = np.sort(key[flat] << np.uint64(low) | np.arange(len(flat), dtype=np.uint64))
            o, k = (k & np.uint64((1 << low) - 1)).astype(np.int64), k >> np.uint64(low)
        else:
            o = np.argsort(key[flat], kind="stable")
            k = key[flat][o]
        new = np.ones(len(o), np.uint64)
        new[1:] = k[1:] != k[:-1]
        rank, order = np.zeros(len(key), np.uint64), flat[o]
        rank[order] = np.cumsum(new)
        return rank, order

    def back(self, row: np.ndarray) -> np.ndarray:
        """Rows of the suffixes one character longer to the left."""
        return row + self.run_shift[np.searchsorted(self.run_start, row, side="right") - 1]

    def earlier(self, owner: np.ndarray) -> np.ndarray:
        """(strings, width): whether ``reach`` characters from a place occur in a string with a smaller owner."""
        out = np.zeros((self.m, self.width), bool)
        row = np.arange(self.m)  # the empty suffixes come first, in the order of their strings
        left = self.length.astype(np.int64).copy()
        live = np.flatnonzero(left > 0)
        while len(live):
            row[live] = self.back(row[live])
            left[live] -= 1
            deep = live[self.length[live] - left[live] >= self.reach]
            out[deep, left[deep]] = self.group_owner[self.group_of_row[row[deep]]] < owner[deep]
            live = live[left[live] > 0]
        return out
