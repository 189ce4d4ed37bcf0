"""One sub-octree as packed components: bitmaps, leaf-local coordinates, attributes. Plain numpy, a level at a time."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa

from ..config import sides
from ..functions.mlv import Mlv, encode, unzigzag, zigzag
from ..functions.succinct import BitVec, leaf_range, tally

Box = tuple[int, int, int, int, int, int]
#: Boxes that are followed together.
TOGETHER = 64


def digits(x: np.ndarray, y: np.ndarray, z: np.ndarray, k: int, side: int) -> np.ndarray:
    at, part = side.bit_length() - 1, k - 1  # both are powers of two
    return (x >> at & part) * (k * k) + (y >> at & part) * k + (z >> at & part)


def paths(x: np.ndarray, y: np.ndarray, z: np.ndarray, parts: Sequence[int], levels: int) -> pa.Array:
    """The first digits of points' paths as strings."""
    s, n = sides(tuple(parts)), len(x)
    held = np.empty((n, levels), np.uint8)
    for j, k in enumerate(parts[:levels]):
        held[:, j] = digits(x, y, z, k, s[j + 1]) + 48
    return pa.LargeStringArray.from_buffers(n, pa.py_buffer(np.arange(n + 1, dtype=np.int64) * levels), pa.py_buffer(held)).cast(pa.string())


def divide(x: np.ndarray, y: np.ndarray, z: np.ndarray, parts: Sequence[int], level: int, limit: int, step: int = 1) -> tuple[np.ndarray, list[tuple[int, np.ndarray, np.ndarray]]]:
    """Points of one box of ``level`` from the top: their leaf levels, and per level the boxes below (a point of each, its points).

    A round looks ``step`` levels deep at the points of boxes that are too heavy still.
    """
    s, h = sides(tuple(parts)), len(parts)
    leaf, live, box, boxes = np.full(len(x), level, np.int32), np.arange(len(x)), np.zeros(len(x), np.int64), []
    while level < h and len(live) > limit:
        deeper = min(level + step, h)
        open_ = np.ones(len(live), bool)
        for j in range(level, deeper):
            k = parts[j]
            _, first, box, counts = np.unique(box * k**3 + digits(x[live], y[live], z[live], k, s[j + 1]), return_index=True, return_inverse=True, return_counts=True)
            own = open_[first]  # boxes whose parent is divided
            boxes.append((j + 1, live[first[own]], counts[own]))
            leaf[live[open_]] = j + 1
            open_ &= (counts > limit)[box]
        live, box, level = live[open_], box[open_], deeper
    return leaf, boxes


def count_up(x: np.ndarray, y: np.ndarray, z: np.ndarray, parts: Sequence[int], level: int, limit: int) -> np.ndarray:
    """Leaf levels of the points of one box of ``level``, from counts of single cells that are added up for all levels."""
    s, h, n = sides(tuple(parts)), len(parts), len(x)
    by = z_order(x, y, z, parts[level:], None)
    x, y, z = x[by], y[by], z[by]
    new = np.ones(n, bool)
    new[1:] = (x[1:] != x[:-1]) | (y[1:] != y[:-1]) | (z[1:] != z[:-1])
    cell = np.flatnonzero(new)
    size = np.diff(np.append(cell, n))
    x, y, z = x[cell], y[cell], z[cell]
    starts = np.zeros(len(cell), bool)
    starts[:1] = True
    leaf, found = np.full(len(cell), h, np.int32), np.zeros(len(cell), bool)
    for j in range(level, h + 1):
        if j > level:
            d = digits(x, y, z, parts[j - 1], s[j])
            starts[1:] |= d[1:] != d[:-1]
        light = (np.add.reduceat(size, np.flatnonzero(starts)) <= limit)[np.cumsum(starts) - 1] if len(cell) else found
        leaf[light & ~found] = j
        found |= light
        if found.all():
            break
    out = np.empty(n, np.int32)
    out[by] = np.repeat(leaf, size)
    return out


def z_order(x: np.ndarray, y: np.ndarray, z: np.ndarray, parts: Sequence[int], pid: np.ndarray | None) -> np.ndarray:
    """Sorting permutation by path, ties by pid; as many digits as 63 bits hold are one key."""
    s = sides(tuple(parts))
    keys, key, bits = [] if pid is None else [pid], np.zeros(len(x), np.int64), 0
    for j, k in reversed(list(enumerate(parts))):
        wide = 3 * (k.bit_length() - 1)
        if bits + wide > 63:
            keys.append(key)
            key, bits = np.zeros(len(x), np.int64), 0
        key |= digits(x, y, z, k, s[j + 1]).astype(np.int64) << bits
        bits += wide
    return np.lexsort([*keys, key])


@dataclass
class Tree:
    """The components, and their parameters. ``parts`` are those of the levels below this tree's root."""

    parts: tuple[int, ...]
    order: str
    root_leaf: bool
    branch: BitVec
    occupied: BitVec
    tally: BitVec
    coordinates: tuple[Mlv, Mlv, Mlv]
    attributes: dict[str, Column]
    permutation: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))

    @property
    def points(self) -> int:
        return self.tally.n

    @property
    def stored(self) -> int:
        """Points with coordinates: those of leaves above the last level, which come first in all arrays."""
        return self.coordinates[0].n


class Column:
    """An attribute in point order: a bitmap or a code, over a shift or zigzag, with presence bits if values are missing."""

    def __init__(self, kind: str, body: BitVec | Mlv, presence: BitVec | None, signed: bool):
        self.kind, self.body, self.presence, self.signed = kind, body, presence, signed

    @classmethod
    def encode(cls, values: np.ndarray, encoding: str = "auto") -> Column:
        """Integers, or floats with NaN for missing values."""
        v = np.asarray(values)
        there = ~np.isnan(v) if v.dtype.kind == "f" else np.ones(len(v), bool)
        presence = None if there.all() else BitVec.from_bits(there)
        v = v[there].astype(np.int64)
        signed = bool(len(v) and v.min() < 0)
        u = zigzag(v) if signed else v.astype(np.uint64)
        if encoding == "bit" or encoding == "auto" and int(u.max(initial=0)) <= 1:
            return cls("bit", BitVec.from_bits(u.astype(np.uint8)), presence, signed)
        return cls("mlv", encode(u), presence, signed)

    def get(self, i: np.ndarray) -> np.ndarray:
        """Values at positions, as floats with NaN where one is missing if the column has such."""
        i = np.asarray(i, np.int64)
        on = self.presence.get(i) if self.presence else np.ones(len(i), bool)
        at = self.presence.rank1(i[on]) if self.presence else i
        u = self.body.get(at).astype(np.uint64)
        v = unzigzag(u) if self.signed else u.astype(np.int64)
        if self.presence is None:
            return v
        out = np.full(len(i), np.nan)
        out[on] = v
        return out

    @property
    def bits(self) -> int:
        return (self.body.n if self.kind == "bit" else self.body.bits) + (self.presence.n if self.presence else 0)

    def to_bytes(self) -> bytes:
        p = self.presence.to_bytes() if self.presence else b""
        return bytes([self.kind == "bit", self.signed]) + len(p).to_bytes(8, "little") + p + self.body.to_bytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> Column:
        n = int.from_bytes(raw[2:10], "little")
        body = raw[10 + n :]
        return cls("bit" if raw[0] else "mlv", BitVec.from_bytes(body) if raw[0] else Mlv.from_bytes(body), BitVec.from_bytes(raw[10 : 10 + n]) if n else None, bool(raw[1]))


def pack(x: np.ndarray, y: np.ndarray, z: np.ndarray, pid: np.ndarray, attributes: dict[str, np.ndarray], parts: tuple[int, ...], limit: int, order: str = "zorder", root_leaf: bool = False) -> Tree:
    """Build the components for points given relative to the tree's root box."""
    s, m = sides(parts), len(x)
    by = z_order(x, y, z, parts, pid)
    x, y, z, pid = x[by], y[by], z[by], pid[by]
    branch, occupied, starts_of, counts_of, sides_of = [], [], [], [], []
    if root_leaf or not parts:
        root_leaf = True
        if m:
            starts_of, counts_of, sides_of = [np.array([0])], [np.array([m])], [np.array([s[0] if parts else 1])]
    else:
        starts, ends = np.array([0]), np.array([m])
        for level, k in enumerate(parts, 1):
            width, side = k**3, s[level]
            sizes = ends - starts
            at = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
            box = np.repeat(np.arange(len(starts)), sizes)
            counts = np.bincount(box * width + digits(x[at], y[at], z[at], k, side), minlength=len(starts) * width).reshape(-1, width)
            first = (starts[:, None] + np.cumsum(counts, 1) - counts).ravel()
            counts = counts.ravel()
            if level < len(parts):
                split = counts > limit
                branch.append(split)
            else:
                split = np.zeros(len(counts), bool)
            full = ~split & (counts > 0)
            occupied.append((counts > 0)[~split])
            starts_of.append(first[full])
            counts_of.append(counts[full])
            sides_of.append(np.full(full.sum(), side))
            starts, ends = first[split], first[split] + counts[split]
            if not len(starts):
                break
    join = lambda a, t: np.concatenate(a).astype(t) if a else np.zeros(0, t)
    starts, counts, side = join(starts_of, np.int64), join(counts_of, np.int64), join(sides_of, np.int64)
    perm = np.repeat(starts - np.concatenate([[0], np.cumsum(counts)[:-1]]) if len(starts) else starts, counts) + np.arange(counts.sum())
    leaf, leaf_side = np.repeat(np.arange(len(counts)), counts), np.repeat(side, counts)
    lx, ly, lz = x[perm] % leaf_side, y[perm] % leaf_side, z[perm] % leaf_side
    if order == "lex":
        again = np.lexsort([pid[perm], lz, ly, lx, leaf])
        perm, lx, ly, lz = perm[again], lx[again], ly[again], lz[again]
    stored = int(counts[side > 1].sum())
    coordinates = tuple(encode(c[:stored]) for c in (lx, ly, lz))
    perm = by[perm]
    return Tree(parts, order, root_leaf, BitVec.from_bits(join(branch, np.uint8)), BitVec.from_bits(join(occupied, np.uint8)), tally(counts), coordinates, {n: Column.encode(v[perm]) for n, v in attributes.items()}, perm)


@dataclass
class Work:
    """What a query has looked at."""

    boxes_visited: int = 0
    branches: int = 0
    empty: int = 0
    leaves: int = 0
    points_checked: int = 0
    coordinates_read: int = 0
    points_out: int = 0
    attr_reads: int = 0


def descend(t: Tree, low: np.ndarray, high: np.ndarray, work: Work) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Occupied leaves that meet boxes ``low, high`` of shape (n, 3), given relative to the root, all boxes a level at a time.

    Gives of each pair the box, the leaf's ordinal, origin and side, and whether it lies fully inside.
    """
    s, m = sides(t.parts), len(low)
    if t.root_leaf:
        q = np.arange(m if t.points else 0)
        work.boxes_visited += m
        inside = (low <= 0).all(1) & (high >= s[0] - 1).all(1)
        return q, np.zeros(len(q), np.int64), np.zeros((len(q), 3), np.int64), np.full(len(q), s[0]), inside[: len(q)]
    q, child, origin = np.arange(m), np.zeros(m, np.int64), np.zeros((m, 3), np.int64)
    found: list[tuple[np.ndarray, ...]] = []
    for level, k in enumerate(t.parts, 1):
        side = s[level]
        a = np.clip((low[q] - origin) // side, 0, k)
        b = np.clip((high[q] - origin) // side, -1, k - 1)
        n = np.maximum(b - a + 1, 0)
        each = n.prod(1)
        box_of = np.repeat(np.arange(len(child)), each)
        i = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
        nz, ny = n[box_of, 2], n[box_of, 1]
        d = np.stack([i // np.maximum(nz * ny, 1), i // np.maximum(nz, 1) % np.maximum(ny, 1), i % np.maximum(nz, 1)], 1) + a[box_of]
        pos = child[box_of] + d[:, 0] * k * k + d[:, 1] * k + d[:, 2]
        at, q = origin[box_of] + d * side, q[box_of]
        work.boxes_visited += len(pos)
        mine = q
        if level < len(t.parts):
            on = t.branch.get(pos) if len(pos) else np.zeros(0, bool)
            h = t.branch.rank0(pos[~on])
            child, origin = (t.branch.rank1(pos[on]) + 1) * t.parts[level] ** 3, at[on]
            if any(p != t.parts[0] for p in t.parts):  # children of earlier levels may be fewer or more
                child = _starts(t, pos[on], level)
            at, mine, q = at[~on], q[~on], q[on]
        else:
            h = pos - t.branch.ones
        keep = t.occupied.get(h) if len(h) else np.zeros(0, bool)
        work.branches += len(child) if level < len(t.parts) else 0
        work.empty += int((~keep).sum())
        found.append((mine[keep], t.occupied.rank1(h[keep]), at[keep], np.full(keep.sum(), side)))
        if level < len(t.parts) and not len(child):
            break
    q, ordinal, at, side = (np.concatenate(c) for c in zip(*found, strict=True))
    inside = ((at >= low[q]).all(1) & (at + side[:, None] - 1 <= high[q]).all(1)) if len(at) else np.zeros(0, bool)
    return q, ordinal, at, side, inside


def _starts(t: Tree, pos: np.ndarray, level: int) -> np.ndarray:
    """Where the children of divided boxes of a level begin, with parts that differ by level."""
    size, start, ones = t.parts[0] ** 3, 0, 1
    for j in range(1, level + 1):  # the levels' first positions
        n = ones * t.parts[j - 1] ** 3
        before = t.branch.rank1(np.array([start]))[0]
        end = start + n
        ones = int(t.branch.rank1(np.array([min(end, t.branch.n)]))[0] - before)
        if j == level:
            return end + (t.branch.rank1(pos) - before) * t.parts[level] ** 3
        start = end
    return np.zeros(0, np.int64) + size


#: Shifts and masks that move the 21 low bits of a number to every third place.
SPREAD = ((32, 0x1F00000000FFFF), (16, 0x1F0000FF0000FF), (8, 0x100F00F00F00F00F), (4, 0x10C30C30C30C30C3), (2, 0x1249249249249249))


def _spread(v: np.ndarray) -> np.ndarray:
    for by, mask in SPREAD:
        v = (v | v << np.uint64(by)) & np.uint64(mask)
    return v


def _codes(local: Sequence[np.ndarray], parts: Sequence[int], side: int) -> np.ndarray:
    """Numbers that order local coordinates below ``side`` (2**21 at most) like their paths."""
    x, y, z = (c.astype(np.uint64) for c in local)
    if all(k == 2 for k in parts):
        return _spread(x) << np.uint64(2) | _spread(y) << np.uint64(1) | _spread(z)
    out, shift = np.zeros(len(x), np.uint64), 0
    for k in reversed(parts):
        if 1 << shift >= side:
            break
        b, mask = k.bit_length() - 1, np.uint64(k - 1)
        at = np.uint64(shift)
        digit = (x >> at & mask) << np.uint64(2 * b) | (y >> at & mask) << np.uint64(b) | z >> at & mask
        out |= digit << np.uint64(3 * shift)
        shift += b
    return out


def _bound(key: Callable[[np.ndarray, np.ndarray], np.ndarray], start: np.ndarray, end: np.ndarray, least: np.ndarray) -> np.ndarray:
    """In each sorted range the first position whose key is ``least`` or more, by halving; ``key`` gets positions and ranges."""
    low, high = start.copy(), end.copy()
    while len(on := np.flatnonzero(low < high)):
        middle = (low[on] + high[on]) // 2
        less = key(middle, on) < least[on]
        low[on[less]], high[on[~less]] = middle[less] + 1, middle[~less]
    return low


def _narrowed(t: Tree, low: np.ndarray, high: np.ndarray, origin: np.ndarray, side: np.ndarray, start: np.ndarray, end: np.ndarray, stop: str, work: Work) -> tuple[np.ndarray, np.ndarray]:
    """The part of each leaf's points that a box can hold, by the order they are in; only the probes are decoded."""
    if not len(start):
        return start, end
    axes = 1 if t.order == "lex" else 3
    long_ = end - start > 2 * axes * np.ceil(np.log2(np.maximum(2, end - start)))  # else halving reads more than it saves
    if not long_.all():
        if long_.any():
            start, end = start.copy(), end.copy()
            start[long_], end[long_] = _narrowed(t, low[long_], high[long_], origin[long_], side[long_], start[long_], end[long_], stop, work)
        return start, end
    corners = [np.clip(c - origin, 0, side[:, None] - 1) for c in (low, high)]  # a row for each leaf
    if stop == "x" and t.order == "lex":
        def key(i: np.ndarray, _: np.ndarray) -> np.ndarray:
            work.coordinates_read += len(i)
            return t.coordinates[0].get(i).astype(np.int64)

        first, last = (c[:, 0] for c in corners)
    elif stop == "code" and t.order == "zorder" and (most := int(side.max())) <= 1 << 21:
        def key(i: np.ndarray, _: np.ndarray) -> np.ndarray:
            work.coordinates_read += 3 * len(i)
            return _codes([c.get(i) for c in t.coordinates], t.parts, most)

        first, last = (_codes(c.T, t.parts, most) for c in corners)
    else:
        return start, end
    begin = _bound(key, start, end, first)
    return begin, _bound(key, begin, end, last + last.dtype.type(1))


def _runs(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which range, and all positions of the ranges."""
    sizes = end - start
    which = np.repeat(np.arange(len(start)), sizes)
    return which, np.repeat(start - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())


def scan(t: Tree, box: Box, where: Sequence[tuple[str, int, int]] = (), columns: Sequence[str] = (), stop: str = "auto", work: Work | None = None, coordinates: bool = True) -> dict[str, np.ndarray]:
    """Points of a closed box relative to the root, in closed ranges of attributes: coordinates and attribute values.

    Without ``coordinates`` those of leaves that lie inside the box are not read at all.
    """
    work = work or Work()
    low, high = np.array(box[:3]), np.array(box[3:])
    _, ordinal, origin, side, inside = descend(t, low[None], high[None], work)
    start, end = leaf_range(t.tally, ordinal) if len(ordinal) else (np.zeros(0, np.int64),) * 2
    work.leaves += len(ordinal)
    stop = {"auto": "x" if t.order == "lex" else "code"}.get(stop, stop)
    part = np.flatnonzero(~inside)  # leaves of single cells meet a box only inside it
    wide = [np.broadcast_to(c, (len(part), 3)) for c in (low, high)]
    which, i = _runs(*_narrowed(t, *wide, origin[part], side[part], start[part], end[part], stop, work))
    leaf = part[which]
    work.points_checked += len(i)
    place = np.zeros((len(i), 3), np.int64)
    for a in range(3):  # an axis is read for what the axes before have left
        work.coordinates_read += len(i)
        place[:, a] = t.coordinates[a].get(i).astype(np.int64) + origin[leaf, a]
        ok = (place[:, a] >= low[a]) & (place[:, a] <= high[a])
        i, leaf, place = i[ok], leaf[ok], place[ok]
    full = np.flatnonzero(inside)
    which, j = _runs(start[full], end[full])
    if coordinates:
        more = origin[full[which]].astype(np.int64).reshape(-1, 3)
        has = j < t.stored
        for a in range(3):
            more[has, a] += t.coordinates[a].get(j[has]).astype(np.int64)
        work.coordinates_read += 3 * int(has.sum())
        place = np.concatenate([place, more])
    i = np.concatenate([i, j])
    values: dict[str, np.ndarray] = {}
    for name, lo, hi in where:
        v = t.attributes[name].get(i)
        work.attr_reads += len(i)
        ok = (v >= lo) & (v <= hi)
        i, place = i[ok], place[ok] if coordinates else place
        values = {n: c[ok] for n, c in values.items()} | {name: v[ok]}
    for name in columns:
        if name not in values:
            values[name] = t.attributes[name].get(i)
            work.attr_reads += len(i)
    work.points_out += len(i)
    return ({a: place[:, k] for k, a in enumerate("xyz")} if coordinates else {}) | {n: values[n] for n in columns} | {"_position": i}


def count(t: Tree, boxes: Sequence[Box], where: Sequence[tuple[str, int, int]] = (), work: Work | None = None) -> np.ndarray:
    """Points of each of several boxes: leaves inside one add the lengths of their ranges, and only those on its border are looked at.

    Boxes are followed together, a level of the tree at a time. With ranges of attributes those of inner leaves are read too.
    """
    work, asked = work or Work(), np.array(boxes, np.int64).reshape(-1, 6)
    out = np.zeros(len(asked), np.int64)
    for first in range(0, len(asked), TOGETHER):
        low, high = asked[first : first + TOGETHER, :3], asked[first : first + TOGETHER, 3:]
        q, ordinal, origin, side, inside = descend(t, low, high, work)
        work.leaves += len(ordinal)
        if not len(ordinal):
            continue
        start, end = leaf_range(t.tally, ordinal)
        part = np.flatnonzero(~inside)
        stop = "x" if t.order == "lex" else "code"
        which, i = _runs(*_narrowed(t, low[q[part]], high[q[part]], origin[part], side[part], start[part], end[part], stop, work))
        leaf = part[which]
        work.points_checked += len(i)
        for a in range(3):
            work.coordinates_read += len(i)
            v = t.coordinates[a].get(i).astype(np.int64) + origin[leaf, a]
            ok = (v >= low[q[leaf], a]) & (v <= high[q[leaf], a])
            i, leaf = i[ok], leaf[ok]
        box = q[leaf]
        if where:
            which, j = _runs(start[inside], end[inside])
            box, i = np.concatenate([box, q[inside][which]]), np.concatenate([i, j])
            for name, lo, hi in where:
                v = t.attributes[name].get(i)
                work.attr_reads += len(i)
                ok = (v >= lo) & (v <= hi)
                box, i = box[ok], i[ok]
        else:
            out[first : first + TOGETHER] += np.bincount(q[inside], (end - start)[inside], len(low)).astype(np.int64)
        out[first : first + TOGETHER] += np.bincount(box, minlength=len(low))
    work.points_out += int(out.sum())
    return out


def point_at(t: Tree, i: int) -> dict[str, int]:
    """One datum by its position in the arrays, without unpacking others: its leaf by rank, its box by the path to it."""
    leaf = int(t.tally.rank1(np.array([i]))[0])
    origin = np.array(_origin(t, leaf))
    local = [int(c.get([i])[0]) for c in t.coordinates] if i < t.stored else [0, 0, 0]
    return dict(zip("xyz", (int(v) for v in origin + local), strict=True)) | {n: c.get(np.array([i]))[0].item() for n, c in t.attributes.items()}


def _origin(t: Tree, leaf: int) -> list[int]:
    """Origin of the leaf with an ordinal: from its flag up to the root."""
    if t.root_leaf:
        return [0, 0, 0]
    h = int(t.occupied.select1(np.array([leaf]))[0])
    zeros = t.branch.n - t.branch.ones
    pos = int(t.branch.select0(np.array([h]))[0]) if h < zeros else h + t.branch.ones
    s, starts, ones, start = sides(t.parts), [], 1, 0
    for k in t.parts:  # first position of each level
        starts.append(start)
        n = ones * k**3
        ones = int(t.branch.rank1(np.array([min(start + n, t.branch.n)]))[0] - t.branch.rank1(np.array([min(start, t.branch.n)]))[0])
        start += n
    level = int(np.searchsorted(starts, pos, side="right"))
    out = np.zeros(3, np.int64)
    while level:
        k = t.parts[level - 1]
        box, d = divmod(pos - starts[level - 1], k**3)
        out += np.array([d // (k * k), d // k % k, d % k]) * s[level]
        level -= 1
        if level:
            before = int(t.branch.rank1(np.array([starts[level - 1]]))[0])
            pos = int(t.branch.select1(np.array([before + box]))[0])
    return out.tolist()


FIELDS = ("t_branch", "t_occupied", "t_tally", "c_x", "c_y", "c_z")


def to_row(t: Tree) -> dict[str, object]:
    return {"parts": list(t.parts), "leaf_order": t.order, "root_leaf": t.root_leaf, "t_branch": t.branch.to_bytes(), "t_occupied": t.occupied.to_bytes(), "t_tally": t.tally.to_bytes()} | {f"c_{a}": c.to_bytes() for a, c in zip("xyz", t.coordinates, strict=True)} | {f"a_{n}": c.to_bytes() for n, c in t.attributes.items()}


def from_row(row: dict[str, object]) -> Tree:
    """A tree of the components that a row has; attributes that were not read are left out."""
    return Tree(tuple(row["parts"]), row["leaf_order"], row["root_leaf"], *(BitVec.from_bytes(row[f]) for f in FIELDS[:3]), tuple(Mlv.from_bytes(row[f]) for f in FIELDS[3:]), {n[2:]: Column.from_bytes(v) for n, v in row.items() if n.startswith("a_") and v is not None})
