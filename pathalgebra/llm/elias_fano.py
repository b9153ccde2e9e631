"""Elias-Fano coding of non-decreasing whole numbers, with select.

``n`` numbers up to ``u`` take about ``n * (2 + log2(u / n))`` bits: the low
bits lie side by side, the high bits are gaps in unary.  Every 256th one of the
upper part has its place noted as a 32-bit offset, so that select reads a few
bytes only and no table of 64-bit numbers exists.
"""

from __future__ import annotations

import struct

import numpy as np

_STEP = 256
_HEAD = struct.Struct("<4sQQBII")
_MAGIC = b"EF01"


def _byte_places() -> np.ndarray:
    """The place of the k-th bit that is set, for every byte."""
    out = np.zeros((256, 8), np.int64)
    for byte in range(256):
        for k, place in enumerate(p for p in range(8) if byte >> p & 1):
            out[byte, k] = place
    return out


_SELECT_IN_BYTE = _byte_places()


class EliasFano:
    def __init__(self, n: int, universe: int, low_bits: int, low: np.ndarray, high: np.ndarray, marks: np.ndarray):
        self.n, self.universe, self.low_bits = n, universe, low_bits
        self.low, self.high, self.marks = low, high, marks
        self._sums: np.ndarray | None = None

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.int64)
        n = len(values)
        universe = int(values[-1]) if n else 0
        low_bits = max(0, (universe // n).bit_length() - 1) if n else 0
        bits = ((values[:, None] >> np.arange(low_bits)) & 1).astype(np.uint8)
        low = np.packbits(bits.reshape(-1), bitorder="little")
        ones = (values >> low_bits) + np.arange(n)
        high = np.zeros((int(ones[-1]) + 1) if n else 0, np.uint8)
        high[ones] = 1
        marks = ones[::_STEP].astype(np.uint32)
        return cls(n, universe, low_bits, low, np.packbits(high, bitorder="little"), marks)

    def to_bytes(self) -> bytes:
        head = _HEAD.pack(_MAGIC, self.n, self.universe, self.low_bits, len(self.low), len(self.high))
        return head + self.low.tobytes() + self.high.tobytes() + self.marks.astype("<u4").tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> EliasFano:
        magic, n, universe, low_bits, a, b = _HEAD.unpack_from(data)
        if magic != _MAGIC:
            raise ValueError("not an Elias-Fano block")
        raw = np.frombuffer(data, np.uint8, offset=_HEAD.size)
        return cls(n, universe, low_bits, raw[:a], raw[a : a + b], np.frombuffer(raw[a + b :].tobytes(), "<u4"))

    def _lower(self, at: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at), np.int64)
        for k in range(self.low_bits):
            bit = at * self.low_bits + k
            out |= ((self.low[bit >> 3].astype(np.int64) >> (bit & 7)) & 1) << k
        return out

    def select(self, i: int) -> int:
        """The i-th number (from 0), from a mark and a short scan."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        mark, left = int(self.marks[i // _STEP]), i % _STEP
        byte = mark >> 3
        bits = np.unpackbits(self.high[byte : byte + 1], bitorder="little")
        bits[: mark & 7] = 0
        while (ones := int(bits.sum())) <= left:
            left -= ones
            byte += 1
            bits = np.unpackbits(self.high[byte : byte + 1], bitorder="little")
        position = byte * 8 + int(np.flatnonzero(bits)[left])
        return ((position - i) << self.low_bits) | int(self._lower(np.array([i]))[0])

    def select_many(self, places: np.ndarray) -> np.ndarray:
        """The numbers at many places at once, from sums of the upper part's bytes."""
        places = np.asarray(places, np.int64)
        if self._sums is None:
            self._sums = np.cumsum(np.bitwise_count(self.high), dtype=np.int64)
        byte = np.searchsorted(self._sums, places, side="right")
        left = places - np.where(byte > 0, self._sums[byte - 1], 0)
        position = byte * 8 + _SELECT_IN_BYTE[self.high[byte], left]
        return ((position - places) << self.low_bits) | self._lower(places)

    def place_of(self, value: int) -> int:
        """The first place whose number isn't below ``value``, by halving with select."""
        low, high = 0, self.n
        while low < high:
            middle = (low + high) // 2
            if self.select(middle) < value:
                low = middle + 1
            else:
                high = middle
        return low

    def decode(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n]
        index = np.arange(self.n)
        return ((ones - index) << self.low_bits) | self._lower(index)
