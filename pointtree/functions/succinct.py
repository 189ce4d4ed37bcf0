"""Bit vectors with rank and select; all operations take and give arrays."""

from __future__ import annotations

import numpy as np


class BitVec:
    """Bits in 64-bit words, with the number of ones before each word as directory."""

    def __init__(self, words: np.ndarray, n: int):
        self.words, self.n = words, n
        counts = np.bitwise_count(words).astype(np.int64)
        self.before = np.concatenate([[0], np.cumsum(counts)])

    @classmethod
    def from_bits(cls, bits: np.ndarray) -> BitVec:
        n = len(bits)
        padded = np.zeros(-(-n // 64) * 64, np.uint8)
        padded[:n] = bits
        return cls(np.packbits(padded, bitorder="little").view("<u8"), n)

    @property
    def ones(self) -> int:
        return int(self.before[-1])

    def get(self, i: np.ndarray) -> np.ndarray:
        i = np.asarray(i, np.int64)
        return (self.words[i >> 6] >> (i & 63).astype(np.uint64)) & np.uint64(1) == 1

    def rank1(self, i: np.ndarray) -> np.ndarray:
        """Ones in [0, i)."""
        i = np.asarray(i, np.int64)
        word, bit = i >> 6, (i & 63).astype(np.uint64)
        part = np.where(bit > 0, self.words[np.minimum(word, max(0, len(self.words) - 1))] & ((np.uint64(1) << bit) - np.uint64(1)), np.uint64(0)) if len(self.words) else np.zeros(i.shape, np.uint64)
        return self.before[word] + np.bitwise_count(part).astype(np.int64)

    def rank0(self, i: np.ndarray) -> np.ndarray:
        return np.asarray(i, np.int64) - self.rank1(i)

    def select1(self, j: np.ndarray) -> np.ndarray:
        """Position of the one with number j, from 0."""
        return self._select(np.asarray(j, np.int64), self.before, self.words)

    def select0(self, j: np.ndarray) -> np.ndarray:
        zeros = np.arange(len(self.before)) * 64 - self.before
        return self._select(np.asarray(j, np.int64), zeros, ~self.words)

    @staticmethod
    def _select(j: np.ndarray, before: np.ndarray, words: np.ndarray) -> np.ndarray:
        w = np.searchsorted(before, j, side="right") - 1
        left, at, word = j - before[w], np.zeros(j.shape, np.int64), words[w].copy()
        for width in (32, 16, 8, 4, 2, 1):
            low = word & np.uint64((1 << width) - 1)
            c = np.bitwise_count(low).astype(np.int64)
            up = left >= c
            left, at = np.where(up, left - c, left), np.where(up, at + width, at)
            word = np.where(up, word >> np.uint64(width), low)
        return w * 64 + at

    def bits(self) -> np.ndarray:
        return np.unpackbits(self.words.view(np.uint8), bitorder="little")[: self.n]

    def to_bytes(self) -> bytes:
        return self.n.to_bytes(8, "little") + self.words.tobytes()[: -(-self.n // 8)]

    @classmethod
    def from_bytes(cls, raw: bytes) -> BitVec:
        n, body = int.from_bytes(raw[:8], "little"), raw[8:]
        return cls(np.frombuffer(body + bytes(-len(body) % 8), "<u8"), n)


def tally(counts: np.ndarray) -> BitVec:
    """Unary counts: c is c - 1 zeros and a one."""
    bits = np.zeros(int(counts.sum()), np.uint8)
    if len(counts):
        bits[np.cumsum(counts) - 1] = 1
    return BitVec.from_bits(bits)


def leaf_range(t: BitVec, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Half-open range of the points of leaf j."""
    j = np.asarray(j, np.int64)
    start = np.where(j > 0, t.select1(np.maximum(j - 1, 0)) + 1, 0)
    return start, t.select1(j) + 1
