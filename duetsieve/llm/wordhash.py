"""Words and word windows of many texts at once as 64-bit hashes, in numpy on the UTF-8 bytes.

Words are maximal runs of bytes outside ``\\x20\\x09-\\x0D`` (in UTF-8 no other character holds such bytes).
A word's hash is a polynomial over its bytes, taken from prefix sums modulo 2^64 and finished by a mixer;
a window's hash is the same over mixed word hashes.  Equal words have equal hashes in every process.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """Finisher of splitmix64."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class _Powers:
    """Powers of an odd base and of its inverse modulo 2^64, as many as asked for."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.zeros(0, U)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(1 << 16, 1 << (n - 1).bit_length())
            made = []
            for b in (self.base, self.inverse):
                x = np.full(size, b, U)
                x[0] = 1
                made.append(np.cumprod(x, dtype=U))
            self.up, self.down = made
        return self.up[:n], self.down[:n]


class Hasher:
    """``fold``: A-Z count as a-z.  Hashers of different ``seed`` are independent."""

    def __init__(self, seed: int = 0, fold: bool = False):
        base = mix(np.arange(1, 5, dtype=U) + U(seed * 1000))
        self.bytes, self.words = _Powers(int(base[0]) | 5), _Powers(int(base[1]) | 5)
        table = mix(np.arange(256, dtype=U) + base[2:3])
        if fold:
            table[65:91] = table[97:123]
        self.table = table

    def words_of(self, flat: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Document index, start byte and hash of each word.  ``ends``: where each text ends in ``flat``."""
        n = len(flat)
        if not n:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, U)
        ink = ~_SPACE[flat]
        first = ink.copy()
        first[1:] &= ~ink[:-1]
        begins = ends[:-1][ends[:-1] < n]
        first[begins] = ink[begins]
        starts = np.flatnonzero(first)
        last = ink.copy()
        last[:-1] &= ~ink[1:]
        stops = ends[ends > 0] - 1
        last[stops] |= ink[stops]
        to = np.flatnonzero(last) + 1
        up, down = self.bytes.upto(n + 1)
        sums = np.zeros(n + 1, U)
        np.cumsum(self.table[flat] * up[:n], out=sums[1:])
        h = mix((sums[to] - sums[starts]) * down[starts] + (to - starts).astype(U) * U(0x9E3779B97F4A7C15))
        return np.searchsorted(ends, starts, side="right"), starts, h

    def windows(self, h: np.ndarray, k: int) -> np.ndarray:
        """Hash of ``k`` words from each place on; windows that cross texts must be masked by the caller."""
        n = len(h) - k + 1
        if n <= 0:
            return np.zeros(0, U)
        up, down = self.words.upto(len(h) + 1)
        sums = np.zeros(len(h) + 1, U)
        np.cumsum(mix(h + U(k)) * up[: len(h)], out=sums[1:])
        return mix((sums[k:] - sums[:n]) * down[:n])


def blocks(texts: pa.LargeStringArray, limit: int = 1 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from, to, bytes, ends) of runs of texts of ``limit`` bytes in all, or of one longer text."""
    offsets = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8) if len(texts) else np.zeros(1, np.int64)
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    a = 0
    while a < len(texts):
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1)
        yield a, b, raw[offsets[a] : offsets[b]], offsets[a + 1 : b + 1] - offsets[a]
        a = b
