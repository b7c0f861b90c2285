"""Elias-Fano coding of ascending integers with a sampled select structure."""

from __future__ import annotations

import struct

import numpy as np

_HEAD = struct.Struct("<QQBQQQ")
_BLOCK = 64  # bytes of high bits between two entries of the select directory
_CHUNK = 1 << 16  # values packed at once, a multiple of 8 so that chunks end on whole bytes


class EliasFano:
    """``n`` ascending values below ``universe`` in about ``2 + log2(universe / n)`` bits each.

    Low bits are packed side by side, high bits are unary-coded in a bit vector. A directory holds the number of
    ones before each block of the bit vector; ``select(i)`` finds the block there and looks through that block only.
    """

    def __init__(self, n: int, universe: int, width: int, low: np.ndarray, high: np.ndarray):
        self.n, self.universe, self.width, self.low, self.high = n, universe, width, low, high
        starts = np.arange(0, len(high), _BLOCK)
        ones = [int(np.bitwise_count(high[a : a + _BLOCK]).sum()) for a in starts]
        self._before = np.cumsum([0, *ones], dtype=np.int64)

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        if n > 1 and (values[1:] < values[:-1]).any():
            raise ValueError("values must ascend")
        universe = int(values[-1]) + 1 if n else 0
        width = max(0, (universe // n).bit_length() - 1) if n else 0
        top = (int(values[-1]) >> width) + n if n else 0
        low, high = [np.empty(0, np.uint8)], np.zeros((top + 7) // 8, np.uint8)
        for a in range(0, n, _CHUNK):
            part = values[a : a + _CHUNK]
            bits = (part[:, None] >> np.arange(width, dtype=np.uint64)).astype(np.uint8) & 1
            low.append(np.packbits(bits.ravel(), bitorder="little"))
            at = (part >> np.uint64(width)).astype(np.int64) + np.arange(a, a + len(part))
            np.bitwise_or.at(high, at >> 3, (1 << (at & 7)).astype(np.uint8))
        return cls(n, universe, width, np.concatenate(low), high)

    def _lows(self, lo: int, hi: int) -> np.ndarray:
        if not self.width:
            return np.zeros(hi - lo, np.uint64)
        a, b = lo * self.width, hi * self.width
        bits = np.unpackbits(self.low[a >> 3 : (b + 7) >> 3], bitorder="little")[a & 7 :][: b - a].reshape(-1, self.width)
        return (bits.astype(np.uint64) << np.arange(self.width, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)

    def values(self, lo: int, hi: int) -> np.ndarray:
        """Values ``lo`` to ``hi - 1``: a select for the first one, and its successors from the blocks that hold them."""
        if not 0 <= lo <= hi <= self.n:
            raise IndexError((lo, hi))
        if lo == hi:
            return np.empty(0, np.int64)
        first = int(np.searchsorted(self._before, lo, side="right")) - 1
        last = int(np.searchsorted(self._before, hi - 1, side="right"))
        bits = np.unpackbits(self.high[first * _BLOCK : last * _BLOCK], bitorder="little")
        skipped = lo - int(self._before[first])
        ones = np.flatnonzero(bits)[skipped : skipped + hi - lo] + first * _BLOCK * 8
        return ((ones - np.arange(lo, hi)) << self.width) | self._lows(lo, hi).astype(np.int64)

    def select(self, i: int) -> int:
        """The i-th value, from 0."""
        return int(self.values(i, i + 1)[0])

    def to_bytes(self) -> bytes:
        head = _HEAD.pack(self.n, self.universe, self.width, len(self.low), len(self.high), 0)
        return head + self.low.tobytes() + self.high.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes, at: int = 0) -> tuple[EliasFano, int]:
        """The structure at ``at`` and the position after it."""
        n, universe, width, n_low, n_high, _ = _HEAD.unpack_from(data, at)
        at += _HEAD.size
        low = np.frombuffer(data, np.uint8, n_low, at)
        high = np.frombuffer(data, np.uint8, n_high, at + n_low)
        return cls(n, universe, width, low, high), at + n_low + n_high
