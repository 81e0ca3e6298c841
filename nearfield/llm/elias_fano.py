"""Elias-Fano lists: a non-decreasing list of n integers below u in about n (2 + log2(u / n)) bits."""

from __future__ import annotations

import struct

import numpy as np

#: Ones between two select samples.
STEP = 256
_HEAD = struct.Struct("<QQIIII")
_COUNT = np.array([bin(i).count("1") for i in range(256)], np.uint8)


class EliasFano:
    """Low bits packed; high parts as a unary bitmap; the place of every 256th one kept for select."""

    def __init__(self, n: int, width: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray, top: int):
        self.n, self.width, self.low, self.high, self.samples, self.top = n, width, low, high, samples, top

    @classmethod
    def of(cls, values) -> EliasFano:
        """``values``: non-negative integers, none below the one before it."""
        v = np.asarray(values, np.uint64)
        n = int(v.size)
        if not n:
            return cls(0, 0, np.zeros(0, np.uint8), np.zeros(0, np.uint8), np.zeros(0, np.uint32), 0)
        if (v[1:] < v[:-1]).any():
            raise ValueError("the list decreases")
        top = int(v[-1])
        width = max(0, ((top + 1) // n).bit_length() - 1)
        shifts = np.arange(width, dtype=np.uint64)
        low = np.packbits(((v[:, None] >> shifts) & np.uint64(1)).astype(np.uint8).ravel(), bitorder="little")
        ones = (v >> np.uint64(width)).astype(np.int64) + np.arange(n)
        bits = np.zeros(int(ones[-1]) + 1, np.uint8)
        bits[ones] = 1
        return cls(n, width, low, np.packbits(bits, bitorder="little"), ones[::STEP].astype(np.uint32), top)

    def __len__(self) -> int:
        return self.n

    def select(self, i: int) -> int:
        """The i-th value, from the nearest sample on: no table of all values."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, left = int(self.samples[i // STEP]), i % STEP
        byte = at >> 3
        now = int(self.high[byte]) >> (at & 7) << (at & 7)
        while (ones := int(_COUNT[now])) <= left:
            left -= ones
            byte += 1
            now = int(self.high[byte])
        for _ in range(left):
            now &= now - 1
        place = byte * 8 + (now & -now).bit_length() - 1
        first = i * self.width
        low = 0
        for k in range(self.width):
            b = first + k
            low |= (int(self.low[b >> 3]) >> (b & 7) & 1) << k
        return (place - i) << self.width | low

    def all(self) -> np.ndarray:
        """Every value, int64."""
        ones = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n]
        out = (ones - np.arange(self.n)) << self.width
        if self.width and self.n:
            bits = np.unpackbits(self.low, bitorder="little")[: self.n * self.width].reshape(self.n, self.width)
            out |= bits.astype(np.int64) @ (np.int64(1) << np.arange(self.width, dtype=np.int64))
        return out.astype(np.int64)

    def to_bytes(self) -> bytes:
        head = _HEAD.pack(self.n, self.top, self.width, self.low.size, self.high.size, self.samples.size)
        return head + self.low.tobytes() + self.high.tobytes() + self.samples.astype("<u4").tobytes()

    @classmethod
    def from_bytes(cls, data, at: int = 0) -> tuple[EliasFano, int]:
        """The list that starts at byte ``at``, and the byte after it."""
        n, top, width, low, high, samples = _HEAD.unpack_from(data, at)
        at += _HEAD.size
        parts = []
        for count, kind in ((low, np.uint8), (high, np.uint8), (samples, np.dtype("<u4"))):
            parts.append(np.frombuffer(data, kind, count, at))
            at += parts[-1].nbytes
        return cls(n, width, *parts, top), at
