"""Elias-Fano coding of non-decreasing integers, with select samples, in numpy.

A value is split at ``low`` bits.  The lower parts are packed; of the upper parts the k-th value sets bit
``upper + k`` of a bitmap, about two bits a value.  Every ``SAMPLE``-th set bit's place is stored, so that
``select`` reads the bitmap from there only.  No table of 64-bit offsets exists.
"""

from __future__ import annotations

import struct

import numpy as np

SAMPLE = 256
_HEAD = struct.Struct("<QQqBxxxxxxx")  # count, words of the bitmap, least value, low bits


def pack_bits(values: np.ndarray, width: int) -> np.ndarray:
    """Little-endian bit string of the values' ``width`` lowest bits."""
    if not width or not len(values):
        return np.zeros(0, np.uint8)
    bits = (values[:, None] >> np.arange(width, dtype=np.uint64)) & np.uint64(1)
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little")


def encode(values: np.ndarray) -> bytes:
    """``values``: int64, non-decreasing."""
    n = len(values)
    least = int(values[0]) if n else 0
    shifted = (values.astype(np.int64) - least).astype(np.uint64)
    span = int(shifted[-1]) + 1 if n else 1
    low = max(0, (span // max(n, 1)).bit_length() - 1)
    upper = (shifted >> np.uint64(low)).astype(np.int64) + np.arange(n, dtype=np.int64)
    words = (int(upper[-1]) // 64 + 1) if n else 0
    bitmap = np.zeros(words * 64, np.uint8)
    bitmap[upper] = 1
    samples = upper[::SAMPLE].astype("<u8")
    lower = pack_bits(shifted & np.uint64((1 << low) - 1), low)
    lower = np.concatenate([lower, np.zeros(-len(lower) % 8 + 8, np.uint8)])  # readable by whole words
    return _HEAD.pack(n, words, least, low) + samples.tobytes() + np.packbits(bitmap, bitorder="little").tobytes() + lower.tobytes()


class Reader:
    def __init__(self, data: bytes):
        self.count, words, self.least, self.low = _HEAD.unpack_from(data)
        at = _HEAD.size
        n_samples = -(-self.count // SAMPLE)
        self.samples = np.frombuffer(data, "<u8", n_samples, at)
        at += 8 * n_samples
        self.bitmap = np.frombuffer(data, np.uint8, words * 8, at)
        at += words * 8
        self.lower = np.frombuffer(data, np.uint8, -1, at)

    def _low(self, k: np.ndarray) -> np.ndarray:
        if not self.low:
            return np.zeros(len(k), np.int64)
        bit = k.astype(np.int64) * self.low
        byte = bit >> 3
        word = np.zeros(len(k), np.uint64)
        for i in range(8):
            word |= self.lower[byte + i].astype(np.uint64) << np.uint64(8 * i)
        word >>= (bit & 7).astype(np.uint64)
        if self.low > 57:  # the value may reach into a ninth byte
            word |= np.where(bit & 7, self.lower[byte + 8].astype(np.uint64) << (np.uint64(64) - (bit & 7).astype(np.uint64)) % np.uint64(64), np.uint64(0))
        return (word & np.uint64((1 << self.low) - 1)).astype(np.int64)

    def select(self, k: int) -> int:
        """The k-th value, from the nearest sample on."""
        if not 0 <= k < self.count:
            raise IndexError(k)
        place, left = int(self.samples[k // SAMPLE]), k % SAMPLE
        byte = place >> 3
        bits = np.unpackbits(self.bitmap[byte : byte + 64], bitorder="little")
        ones = np.flatnonzero(bits)
        ones = ones[ones >= place - 8 * byte]
        take = 64
        while len(ones) <= left:  # a wide gap: read on
            take *= 2
            ones = np.flatnonzero(np.unpackbits(self.bitmap[byte : byte + take], bitorder="little"))
            ones = ones[ones >= place - 8 * byte]
        upper = 8 * byte + int(ones[left]) - k
        return self.least + (upper << self.low) + int(self._low(np.array([k]))[0])

    def some(self, a: int, b: int) -> np.ndarray:
        """Values ``a`` to ``b - 1``, decoded from the nearest sample on; memory follows their number and span."""
        if not 0 <= a < b <= self.count:
            raise IndexError((a, b))
        place = int(self.samples[a // SAMPLE])
        byte, need, take = place >> 3, a % SAMPLE + b - a, (b - a) // 2 + 64
        while True:
            ones = np.flatnonzero(np.unpackbits(self.bitmap[byte : byte + take], bitorder="little"))
            ones = ones[ones >= place - 8 * byte]
            if len(ones) >= need:
                break
            take *= 2  # a wide gap: read on
        k = np.arange(a, b)
        return self.least + ((8 * byte + ones[a % SAMPLE : need] - k) << self.low) + self._low(k)

    def all(self) -> np.ndarray:
        upper = np.flatnonzero(np.unpackbits(self.bitmap, bitorder="little")).astype(np.int64) - np.arange(self.count)
        return self.least + (upper << self.low) + self._low(np.arange(self.count))
