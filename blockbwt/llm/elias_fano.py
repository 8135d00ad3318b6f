"""Elias-Fano coding of a non-decreasing sequence, with select.

A value is split into `low_bits` low bits, stored as they are, and a high part,
stored in unary in one bit vector: bit `high + i` is set for value i. Every
SAMPLE-th set bit's place is kept, so select(i) scans a few bytes. The space is
about 2 + log2(universe / n) bits a value; no 64-bit table is kept.
"""

from __future__ import annotations

import struct

import numpy as np

SAMPLE = 256
_HEAD = struct.Struct("<QBQQQ")


class EliasFano:
    def __init__(self, n: int, low_bits: int, first: int, low: bytes, high: bytes, samples: np.ndarray):
        self.n, self.low_bits, self.first, self.low, self.high, self.samples = n, low_bits, first, low, high, samples

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        """values: integers, non-decreasing; negative ones are stored against the first."""
        values = np.asarray(values, np.int64)
        n = len(values)
        if not n:
            return cls(0, 0, 0, b"", b"", np.zeros(0, np.uint32))
        if (values[1:] < values[:-1]).any():
            raise ValueError("values must not decrease")
        first = int(values[0])
        off = values.view(np.uint64) - np.uint64(first & 0xFFFFFFFFFFFFFFFF)
        low_bits = max(0, (int(off[-1]) // n).bit_length() - 1)
        low = off & np.uint64((1 << low_bits) - 1)
        bits = (low[:, None] >> np.arange(low_bits, dtype=np.uint64)).astype(np.uint8) & 1
        ones = (off >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        vector = np.zeros(int(ones[-1]) + 1, np.uint8)
        vector[ones] = 1
        return cls(n, low_bits, first, np.packbits(bits, bitorder="little").tobytes(), np.packbits(vector, bitorder="little").tobytes(), ones[::SAMPLE].astype(np.uint32))

    def _low_of(self, i: int) -> int:
        at, width = i * self.low_bits, self.low_bits
        return int.from_bytes(self.low[at // 8 : (at + width + 7) // 8], "little") >> (at % 8) & ((1 << width) - 1)

    def select(self, i: int) -> int:
        """Value i, read from its sample on."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        place, left = int(self.samples[i // SAMPLE]), i % SAMPLE
        byte = place // 8
        now = self.high[byte] >> (place % 8) << (place % 8)
        while (ones := now.bit_count()) <= left:
            left -= ones
            byte += 1
            now = self.high[byte]
        for _ in range(left):
            now &= now - 1
        one = byte * 8 + (now & -now).bit_length() - 1
        value = ((one - i) << self.low_bits | self._low_of(i)) + self.first
        return value

    def rank(self, value: int) -> int:
        """How many values are below `value`: a search by select."""
        low, high = 0, self.n
        while low < high:
            middle = (low + high) // 2
            if self.select(middle) < value:
                low = middle + 1
            else:
                high = middle
        return low

    def all(self) -> np.ndarray:
        if not self.n:
            return np.zeros(0, np.int64)
        ones = np.flatnonzero(np.unpackbits(np.frombuffer(self.high, np.uint8), bitorder="little"))[: self.n]
        out = (ones - np.arange(self.n)).astype(np.uint64) << np.uint64(self.low_bits)
        if self.low_bits:
            bits = np.unpackbits(np.frombuffer(self.low, np.uint8), count=self.n * self.low_bits, bitorder="little").reshape(self.n, -1)
            out |= (bits.astype(np.uint64) << np.arange(self.low_bits, dtype=np.uint64)).sum(1, dtype=np.uint64)
        return (out + np.uint64(self.first & 0xFFFFFFFFFFFFFFFF)).view(np.int64)

    def to_bytes(self) -> bytes:
        head = _HEAD.pack(self.n, self.low_bits, self.first & 0xFFFFFFFFFFFFFFFF, len(self.low), len(self.high))
        return head + self.low + self.high + self.samples.astype("<u4").tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> EliasFano:
        n, low_bits, first, a, b = _HEAD.unpack_from(data)
        at = _HEAD.size
        first -= (first >> 63) << 64
        return cls(n, low_bits, first, data[at : at + a], data[at + a : at + a + b], np.frombuffer(data, "<u4", -1, at + a + b))
