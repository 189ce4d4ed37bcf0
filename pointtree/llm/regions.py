"""The metric join inside one region, in numpy: Voronoi cells, triangle windows and pivots.

Two metrics are used. The size of the symmetric difference of two sets is one, and the Hamming distance of their
parity sketches (bit i tells whether an odd number of elements falls into bucket i) never exceeds it, so that windows
of the triangle inequality on sketches lose no link. The other is the Jaccard distance of the sets themselves.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bits of a sketch at least; sketches have at least twice as many bits as their set has elements.
LEAST_BITS = 512
#: Sets from which on a cell is split by pivots, the pivots of a split, and what part of a cell a smaller cell may hold.
SMALL, PIVOTS, SHRINK = 64, 8, 0.75
#: Pairs times words that one comparison holds.
HELD = 1 << 21


def width(n: int) -> int:
    """Bits of the sketch of a set of n elements."""
    return max(LEAST_BITS, 1 << (2 * n - 1).bit_length())


def parity(s: np.ndarray, bits: int) -> bytes:
    """The parity sketch of a set of hashes."""
    odd = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def fold(raw: bytes) -> bytes:
    """The sketch of half the width."""
    x = np.frombuffer(raw, np.uint8)
    return (x[: len(x) // 2] ^ x[len(x) // 2 :]).tobytes()


def _bounds(sizes: np.ndarray, percent: int) -> np.ndarray:
    """The largest symmetric difference of a set and one that it links with."""
    return sizes * (100 - percent) // percent


def _pairs(x: np.ndarray, sizes: np.ndarray, labels: np.ndarray, percent: int, first: np.ndarray, second: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (i of first, j of second, i < j) of different labels whose sketches and sizes allow a link."""
    bound = _bounds(sizes, percent)
    step = max(1, HELD // max(1, len(second) * x.shape[1]))
    for at in range(0, len(first), step):
        i = first[at : at + step]
        far = np.bitwise_count(x[i][:, None, :] ^ x[second][None, :, :]).sum(2, dtype=np.int64)
        ok = (far <= np.minimum(bound[i][:, None], bound[second][None, :])) & (labels[i][:, None] != labels[second][None, :]) & (i[:, None] < second[None, :])
        ok &= 100 * np.minimum(sizes[i][:, None], sizes[second][None, :]) >= percent * np.maximum(sizes[i][:, None], sizes[second][None, :])
        a, b = np.nonzero(ok)
        yield i[a], second[b]


def _cells(x: np.ndarray, sizes: np.ndarray, labels: np.ndarray, percent: int, at: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Candidate pairs of the sets ``at``: Voronoi cells of a few pivots, with the sets near their borders, recursively.

    A set at distance d of its own pivot links with one of another cell only if it is within d + 2 * radius of that
    cell's pivot. Cells of one label are done. Where distances don't tell the sets apart, their pairs are compared.
    """
    counts = np.unique(labels[at], return_counts=True)
    if len(counts[0]) < 2:
        return
    if len(at) > SMALL:
        pivots = at[:: -(-len(at) // PIVOTS)]
        far = np.bitwise_count(x[at][:, None, :] ^ x[pivots][None, :, :]).sum(2, dtype=np.int64)
        inside = far <= far.min(1, keepdims=True) + 2 * _bounds(sizes[at], percent)[:, None]
        if inside.sum(0).max() <= SHRINK * len(at):
            for k in range(len(pivots)):
                yield from _cells(x, sizes, labels, percent, at[inside[:, k]])
            return
    # of the largest label's sets, pairs among themselves are no candidates
    most = labels[at] == counts[0][np.argmax(counts[1])]
    rest = at[~most]
    for first, second in ((rest, rest), (rest, at[most])):
        for i, j in _pairs(x, sizes, labels, percent, first, second):
            yield i, j
    for i, j in _pairs(x, sizes, labels, percent, at[most], rest):
        yield i, j


def candidates(sizes: np.ndarray, sketches: list[bytes], labels: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i, j) with i < j, of different labels, that the sketches don't tell to be no links."""
    n = len(sizes)
    if n <= 12:  # most regions: whole numbers are quicker than arrays
        ints, out = [int.from_bytes(s, "little") for s in sketches], []
        size, label, bound = sizes.tolist(), labels.tolist(), _bounds(sizes, percent).tolist()
        for j in range(1, n):
            for i in range(j):
                small, large = (i, j) if size[i] <= size[j] else (j, i)
                if label[i] != label[j] and 100 * size[small] >= percent * size[large]:
                    a, b = ints[small], ints[large]
                    if len(sketches[small]) < len(sketches[large]):
                        half = 8 * len(sketches[small])
                        b = (b >> half) ^ (b & ((1 << half) - 1))
                    if (a ^ b).bit_count() <= bound[small]:
                        out.append((i, j))
        pairs = np.array(out, np.int64).reshape(-1, 2)
        return pairs[:, 0], pairs[:, 1]
    widths = np.array([len(s) for s in sketches])
    found_i, found_j = [], []
    for w in np.unique(widths):  # sets that link have sketches of one width or of twice as much
        own, twice = np.flatnonzero(widths == w), np.flatnonzero(widths == 2 * w)
        at = np.concatenate([own, twice])
        x = np.frombuffer(b"".join([*[sketches[k] for k in own], *[fold(sketches[k]) for k in twice]]), np.uint64).reshape(len(at), -1)
        for i, j in _cells(x, sizes[at], labels[at], percent, np.arange(len(at))):
            mine = i < len(own)  # pairs of the wider ones come at their own width
            i, j = at[i[mine]], at[j[mine]]
            found_i.append(np.minimum(i, j))
            found_j.append(np.maximum(i, j))
    if not found_i:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    both = np.unique(np.concatenate(found_i) * n + np.concatenate(found_j))
    return both // n, both % n


def roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The least member of each node's component under the edges (i, j)."""
    label = np.arange(n)
    while len(i):
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, label[i], low)
        np.minimum.at(new, label[j], low)
        new = new[new]
        while (new[new] != new).any():
            new = new[new]
        new = new[label]
        if (new == label).all():
            break
        label = new
    return label


def clusters(nodes: np.ndarray, sizes: np.ndarray, sketches: list[bytes], labels: np.ndarray, percent: int) -> list[tuple[bytes, np.ndarray]]:
    """(fingerprint, nodes) of the groups of a region's sets that candidate pairs join."""
    i, j = candidates(sizes, sketches, labels, percent)
    if not len(i):
        return []
    if len(nodes) == 2:
        both = np.sort(nodes)
        return [(both.tobytes(), both)]
    root = roots(len(nodes), i, j)
    touched = np.unique(np.concatenate([i, j]))
    order = touched[np.argsort(root[touched], kind="stable")]
    cuts = np.flatnonzero(root[order][1:] != root[order][:-1]) + 1
    out = []
    for part in np.split(order, cuts):
        members = np.unique(nodes[part])
        out.append((members.tobytes() if len(members) == 2 else hashlib.blake2b(members.tobytes(), digest_size=16).digest(), members))
    return out


def links(nodes: np.ndarray, labels: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links enough to join what links join, each verified on whole sets.

    The set with the most candidates is the pivot; its Jaccard distances decide its links, and by the triangle
    inequality two sets whose distances to it differ by more than the radius are no candidates any more.
    """
    sizes = np.array([len(s) for s in sets], np.int64)
    if len(nodes) == 2:
        i, j = np.array([0]), np.array([1])
    else:
        i, j = candidates(sizes, [parity(s, width(len(s))) for s in sets], labels, percent)
    label, out, radius = np.unique(labels, return_inverse=True)[1], [], 1 - percent / 100 + 1e-9
    far = np.full(len(nodes), np.nan)
    while len(i):
        pivot = int(np.bincount(np.concatenate([i, j]), minlength=len(nodes)).argmax())
        mine = (i == pivot) | (j == pivot)
        other = i[mine] + j[mine] - pivot
        p, flat = sets[pivot], np.concatenate([sets[k] for k in other])
        at = np.searchsorted(p, flat)
        hit = p[np.minimum(at, len(p) - 1)] == flat
        overlap = np.add.reduceat(hit.astype(np.int64), np.cumsum(sizes[other]) - sizes[other])
        union = sizes[other] + len(p) - overlap
        near = 100 * overlap >= percent * union
        out += [(int(nodes[pivot]), int(nodes[k])) for k in other[near]]
        label[np.isin(label, label[other[near]])] = label[pivot]
        far[:] = np.nan
        far[other] = 1 - overlap / union
        keep = ~mine & (label[i] != label[j]) & ~(np.abs(far[i] - far[j]) > radius)
        i, j = i[keep], j[keep]
    return out


def runs(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Rows that come sorted by ``key``, a table for each value."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        if not b.num_rows:
            continue
        keys = b.column(b.schema.get_field_index(key))
        if pa.types.is_integer(keys.type):
            k = keys.to_numpy()
            cuts = (np.flatnonzero(k[1:] != k[:-1]) + 1).tolist()
        else:
            k = keys.to_pylist()
            cuts = [n for n in range(1, len(k)) if k[n] != k[n - 1]]
        for low, high in zip([0, *cuts], [*cuts, b.num_rows], strict=True):
            if held and k[low] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(low, high - low))
            last = k[low]
    if held:
        yield pa.Table.from_batches(held)
