"""Elias-Fano coding of monotone integer sequences, searched in place in a memory-mapped buffer.

A value's upper part is written in unary (one set bit for each value; its place less its number is the upper part), its ``low`` lower bits as they are,
packed. Size: about 2 + log2(universe / n) bits a value. On opening, a directory counts the set bits before each 64-bit word; a bit is then selected by a
search among words and broadword arithmetic inside one, and lower bits are read through an unaligned window. All operations take arrays of
questions; none decodes the sequence.
"""

from __future__ import annotations

import numpy as np

PIECE = 1 << 14
_ONES, _HIGH = np.uint64(0x0101010101010101), np.uint64(0x8080808080808080)
_U = np.uint64
#: place of the r-th set bit of a byte
_SELECT = np.array([[([k for k in range(8) if x >> k & 1] + [8] * 8)[r] for r in range(8)] for x in range(256)], np.uint8)


def _select_in_word(x: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Place of the r-th set bit of 64-bit words, counted from the lowest."""
    s = x - (x >> _U(1) & _U(0x5555555555555555))
    s = (s & _U(0x3333333333333333)) + (s >> _U(2) & _U(0x3333333333333333))
    s = (s + (s >> _U(4)) & _U(0x0F0F0F0F0F0F0F0F)) * _ONES  # byte k: set bits of bytes 0 to k
    r = r.astype(np.uint64)
    byte = (((r * _ONES | _HIGH) - s & _HIGH) >> _U(7)) * _ONES >> _U(56)
    shift = byte << _U(3)
    before = (s << _U(8)) >> shift & _U(255)
    return (shift + _SELECT[x >> shift & _U(255), r - before]).astype(np.int64)


class EliasFano:
    def __init__(self, n: int, low: int, upper: np.ndarray, lower: np.ndarray):
        """upper: 64-bit words; lower: bytes, with eight more behind them."""
        self.n, self.low, self.upper, self.lower = n, low, upper, lower
        self._ones = np.concatenate([[0], np.cumsum(np.bitwise_count(upper), dtype=np.int64)])
        self._zeros = 64 * np.arange(len(self._ones)) - self._ones
        self._window = np.ndarray((max(len(lower) - 7, 0),), "<u8", lower, strides=(1,))

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        top = int(values[-1]) if n else 0
        low = max(0, (top // n).bit_length() - 1) if n else 0
        place = (values >> _U(low)).astype(np.int64) + np.arange(n)
        bits = np.zeros(-(-(int(place[-1]) + 2) // 64) * 64 if n else 0, np.uint8)  # one zero at least behind the last value
        bits[place] = 1
        shifts = np.arange(low, dtype=np.uint64)
        lower = [np.packbits(((values[i : i + PIECE, None] >> shifts) & _U(1)).astype(np.uint8), bitorder="little") for i in range(0, n, PIECE)] if low else []
        size = sum(map(len, lower))
        return cls(n, low, np.packbits(bits, bitorder="little").view("<u8"), np.concatenate([*lower, np.zeros(16 - size % 8, np.uint8)]))

    def to_bytes(self) -> bytes:
        return np.array([self.n, self.low, len(self.upper), len(self.lower)], "<i8").tobytes() + self.upper.tobytes() + self.lower.tobytes()

    @classmethod
    def read(cls, buffer: memoryview | bytes, at: int = 0) -> tuple[EliasFano, int]:
        """(sequence, place after it)."""
        n, low, u, v = np.frombuffer(buffer, "<i8", 4, at).tolist()
        at += 32
        return cls(n, low, np.frombuffer(buffer, "<u8", u, at), np.frombuffer(buffer, np.uint8, v, at + 8 * u)), at + 8 * u + v

    def _select1(self, i: np.ndarray) -> np.ndarray:
        w = np.searchsorted(self._ones, i, side="right") - 1
        return 64 * w + _select_in_word(self.upper[w], i - self._ones[w])

    def _select0(self, i: np.ndarray) -> np.ndarray:
        w = np.searchsorted(self._zeros, i, side="right") - 1
        return 64 * w + _select_in_word(~self.upper[w], i - self._zeros[w])

    def _lows(self, i: np.ndarray) -> np.ndarray:
        bit = i * self.low
        return self._window[bit >> 3].astype(np.uint64) >> (bit & 7).astype(np.uint64) & _U((1 << self.low) - 1)

    def at(self, i: np.ndarray) -> np.ndarray:
        """Values at places below n."""
        i = np.asarray(i, np.int64)
        return (self._select1(i) - i).astype(np.uint64) << _U(self.low) | self._lows(i)

    def _below(self, h: np.ndarray) -> np.ndarray:
        """How many values have an upper part below h."""
        out = np.where(h > 0, self.n, 0)
        inside = np.flatnonzero((h > 0) & (h <= self._zeros[-1]))
        out[inside] = self._select0(h[inside] - 1) - h[inside] + 1
        return out

    def successor(self, low: np.ndarray, high: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first place in [low, high) whose value is at least x, or high; whether the value there is x).

        The upper part names a short range of places; only lower bits are compared inside it.
        """
        x = np.asarray(x, np.uint64)
        if not self.n:
            return np.asarray(high), np.zeros(len(x), bool)
        h = (x >> _U(self.low)).astype(np.int64)
        a, b = np.clip(self._below(h), low, high), np.clip(self._below(h + 1), low, high)
        want, stop = x & _U((1 << self.low) - 1), b.copy()
        open_ = np.flatnonzero(a < b)
        while len(open_):
            mid = (a[open_] + b[open_]) >> 1
            right = self._lows(mid) < want[open_]
            a[open_[right]] = mid[right] + 1
            b[open_[~right]] = mid[~right]
            open_ = open_[a[open_] < b[open_]]
        hit = a < stop
        hit[hit] = self._lows(a[hit]) == want[hit]
        return a, hit
