"""Paths from the root to a box: one digit per level, x the most significant part of a digit.

As a string a path sorts bytewise like the boxes' depth-first order, a prefix is an ancestor, and equal prefixes join.
As two longs it is 16 bytes for any depth that a grid of 2**42 needs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import sides
from .quantize import AXES, div


def _log2(k: int) -> int:
    return k.bit_length() - 1


def digit(level: int, parts: tuple[int, ...], x: str = "x", y: str = "y", z: str = "z") -> Column:
    """Which child of its box of level - 1 a point lies in; levels count from 1."""
    k, side = parts[level - 1], sides(parts)[level]
    part = lambda c: F.shiftright(F.col(c), _log2(side)).bitwiseAND(F.lit(k - 1))
    return part(x) * (k * k) + part(y) * k + part(z)


def path_of(parts: tuple[int, ...], x: str = "x", y: str = "y", z: str = "z") -> Column:
    return F.concat(*[F.char(digit(j, parts, x, y, z) + 48) for j in range(1, len(parts) + 1)])


def prefix_of(parts: tuple[int, ...], levels: int, from_path: bool = False) -> Column:
    """The first digits of a point's path, from the coordinates or from ``path`` where rows have it."""
    if from_path:
        return F.substring("path", 1, levels) if levels else F.lit("")
    return F.concat(F.lit(""), *[F.char(digit(j, parts) + 48) for j in range(1, levels + 1)])


def with_path(df: DataFrame, parts: tuple[int, ...]) -> DataFrame:
    return df.withColumn("path", path_of(parts))


def packed_path(parts: tuple[int, ...]) -> tuple[Column, Column]:
    """Two longs that order like the path (two parts per axis, up to 42 levels): the upper levels, then the lower ones."""
    if any(k != 2 for k in parts) or len(parts) > 42:
        raise ValueError("packed paths have two parts per axis and up to 42 levels")
    h = len(parts)
    top = max(0, h - 21)

    def fold(levels: range) -> Column:
        out = F.lit(0).cast("long")
        for j in levels:
            out = F.shiftleft(out, 3).bitwiseOR(digit(j, parts))
        return out

    return fold(range(1, top + 1)), fold(range(top + 1, h + 1))


def common_levels(a: tuple[Column, Column, Column], b: tuple[Column, Column, Column], parts: tuple[int, ...]) -> Column:
    """How many levels two points share a box on: from the highest bit in which a coordinate differs."""
    differs = a[0].bitwiseXOR(b[0]).bitwiseOR(a[1].bitwiseXOR(b[1])).bitwiseOR(a[2].bitwiseXOR(b[2]))
    bits = F.when(differs == 0, 0).otherwise(F.length(F.bin(differs)))
    out, s = F.lit(0), sides(parts)
    for level in range(1, len(parts) + 1):
        out = out + (bits <= _log2(s[level])).cast("int")
    return out


def node_origin(path: str, level: Column, parts: tuple[int, ...], axis: int) -> Column:
    """The least coordinate on an axis of the box that a path of ``level`` digits names."""
    s, out = sides(parts), F.lit(0).cast("long")
    for j, k in enumerate(parts, 1):
        d = F.ascii(F.substring(path, j, 1)) - 48
        part = (div(d, F.lit(k * k)), div(d, F.lit(k)) % k, d % k)[axis]
        out = out + F.when(level >= j, part.cast("long") * F.lit(s[j])).otherwise(0)
    return out


def with_box(nodes: DataFrame, parts: tuple[int, ...]) -> DataFrame:
    """Adds origin and side of each node's box."""
    s = sides(parts)
    level_side = F.element_at(F.array(*[F.lit(v).cast("long") for v in s]), F.col("level").cast("int") + 1)
    return nodes.withColumns({f"{a}0": node_origin("path", F.col("level"), parts, i) for i, a in enumerate(AXES)} | {"side": level_side})
