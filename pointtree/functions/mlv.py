"""Multi-level variable-length codes for naturals, directly addressable.

Level i keeps chunk i of every value that is still alive, and a bit that says whether the value goes on; a value's place
on the next level is the rank of that bit. A slice of values is a slice on every level.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np

from .succinct import BitVec


def best_widths(lengths: np.ndarray) -> list[int]:
    """Chunk widths with the least total bits for a histogram of bit lengths (index: length, at least 1)."""
    top = int(np.flatnonzero(lengths).max(initial=1)) or 1
    longer = lambda s: int(lengths.sum()) if s == 0 else int(lengths[s + 1 :].sum())
    cost, cut = {top: 0}, {}
    for s in range(top - 1, -1, -1):
        n = longer(s)
        cost[s], cut[s] = min((n * (e - s + (e < top)) + cost[e], e) for e in range(s + 1, top + 1))
    out, s = [], 0
    while s < top:
        out.append(cut[s] - s)
        s = cut[s]
    return out


def bit_lengths(values: np.ndarray) -> np.ndarray:
    """Bits of each value, one at least."""
    v, out = values.astype(np.uint64), np.ones(len(values), np.int64)
    for shift in (32, 16, 8, 4, 2, 1):
        big = v >> np.uint64(shift) > 0
        out[big] += shift
        v = np.where(big, v >> np.uint64(shift), v)
    return out


def _put(chunks: np.ndarray, width: int) -> np.ndarray:
    bits = (chunks[:, None] >> np.arange(width - 1, -1, -1, dtype=np.uint64)) & np.uint64(1)
    return np.packbits(bits.astype(np.uint8).ravel())


def _take(raw: np.ndarray, i: np.ndarray, width: int) -> np.ndarray:
    at = i * width
    if width > 57:  # wide chunks in two halves
        half = width // 2
        return (_bits(raw, at, half) << np.uint64(width - half)) | _bits(raw, at + half, width - half)
    return _bits(raw, at, width)


def _bits(raw: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """Up to 57 bits from any bit on: eight bytes are read as one number, and what is before and behind is shifted out."""
    words = np.ndarray((max(0, len(raw) - 7),), ">u8", raw, strides=(1,))[at >> 3].astype(np.uint64)
    return (words << (at & 7).astype(np.uint64)) >> np.uint64(64 - width)


class Mlv:
    def __init__(self, n: int, widths: list[int], chunks: list[np.ndarray], more: list[BitVec]):
        self.n, self.widths, self.chunks, self.more = n, widths, chunks, more

    @property
    def bits(self) -> int:
        """Bits of chunks and continuation flags, without directories."""
        alive = [self.n, *[m.ones for m in self.more]]
        return sum(a * w for a, w in zip(alive, self.widths, strict=True)) + sum(m.n for m in self.more)

    def get(self, index: Iterable[int]) -> np.ndarray:
        i = np.asarray(index, np.int64)
        out, alive, shift = np.zeros(len(i), np.uint64), np.arange(len(i)), 0
        for k, w in enumerate(self.widths):
            if not len(alive):
                break
            out[alive] |= _take(self.chunks[k], i, w) << np.uint64(shift)
            shift += w
            if k < len(self.more):
                on = self.more[k].get(i)
                alive, i = alive[on], self.more[k].rank1(i[on])
        return out

    def slice(self, a: int, b: int) -> np.ndarray:
        return self.get(np.arange(a, b))

    def to_bytes(self) -> bytes:
        pieces = [self.n.to_bytes(8, "little"), bytes([len(self.widths), *self.widths])]
        for c in self.chunks:
            pieces += [len(c).to_bytes(8, "little"), c.tobytes()]
        for m in self.more:
            raw = m.to_bytes()
            pieces += [len(raw).to_bytes(8, "little"), raw]
        return b"".join(pieces)

    @classmethod
    def from_bytes(cls, raw: bytes) -> Mlv:
        n, levels = int.from_bytes(raw[:8], "little"), raw[8]
        widths, at = list(raw[9 : 9 + levels]), 9 + levels
        blobs = []
        for _ in range(2 * levels - 1):
            size = int.from_bytes(raw[at : at + 8], "little")
            blobs.append(raw[at + 8 : at + 8 + size])
            at += 8 + size
        return cls(n, widths, [np.frombuffer(b, np.uint8) for b in blobs[:levels]], [BitVec.from_bytes(b) for b in blobs[levels:]])


def encode(values: Iterable[int], widths: str | list[int] = "auto") -> Mlv:
    """Code naturals below 2**62 with given chunk widths (the last repeats) or the best ones."""
    v = np.asarray(values, np.uint64)
    lengths = bit_lengths(v)
    if widths == "auto":
        widths = best_widths(np.bincount(lengths, minlength=65)) if len(v) else [1]
    top, given, used = int(lengths.max(initial=1)), list(widths), []
    while sum(used) < top:
        used.append(given.pop(0) if len(given) > 1 else given[0])
    chunks, more, left = [], [], v
    for k, w in enumerate(used):
        chunks.append(np.append(_put(left & np.uint64((1 << w) - 1), w), np.zeros(9, np.uint8)))
        left = left >> np.uint64(w)
        if k + 1 < len(used):
            on = left > 0
            more.append(BitVec.from_bits(on))
            left = left[on]
    return Mlv(len(v), used, chunks, more)


def zigzag(v: np.ndarray) -> np.ndarray:
    v = np.asarray(v, np.int64)
    return ((v << 1) ^ (v >> 63)).astype(np.uint64)


def unzigzag(v: np.ndarray) -> np.ndarray:
    v = np.asarray(v, np.uint64)
    return ((v >> np.uint64(1)) ^ (np.uint64(0) - (v & np.uint64(1)))).astype(np.int64)
