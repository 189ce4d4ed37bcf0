"""Real coordinates to a natural grid and back.

A frame is fitted by one aggregate and enters plans as literals. Fixed-scale axes multiply by an integer inverse scale
and round; span axes stretch integers so that the largest becomes the target. Both subtract the minimum first or last,
so that every coordinate is a natural number.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import TreeConfig, sides

AXES = ("x", "y", "z")
RAW = ("rx", "ry", "rz")
Box = tuple[int, int, int, int, int, int]


@dataclass(frozen=True)
class Fixed:
    """Real times ``inverse`` rounded, minus the least."""

    inverse: tuple[int, int, int] = (1, 1, 1)


@dataclass(frozen=True)
class Span:
    """Integer axes stretched to 0..target each."""

    target: tuple[int, int, int] = (10**9, 10**9, 10**9)
    inverse: tuple[int, int, int] = (1, 1, 1)


@dataclass(frozen=True)
class Frame:
    policy: Fixed | Span
    low: tuple[int, int, int]
    high: tuple[int, int, int]
    count: int

    @property
    def extent(self) -> tuple[int, int, int]:
        """Largest grid coordinate of each axis."""
        if isinstance(self.policy, Span):
            return tuple(t if b > a else 0 for t, a, b in zip(self.policy.target, self.low, self.high, strict=True))
        return tuple(b - a for a, b in zip(self.low, self.high, strict=True))

    def parts(self, config: TreeConfig) -> tuple[int, ...]:
        return config.parts(max(self.extent))

    def narrow_axes(self, config: TreeConfig, leaf_level: int) -> list[str]:
        """Axes that boxes of a level are taller than: the tree can't prune along them (a span policy helps)."""
        side = sides(self.parts(config))[min(leaf_level, len(self.parts(config)))]
        return [a for a, e in zip(AXES, self.extent, strict=True) if e < side]


def scaled(c: str | Column, inverse: int) -> Column:
    """The integer that a real stands for."""
    return F.round((F.col(c) if isinstance(c, str) else c) * F.lit(inverse)).cast("long")


def valid(df: DataFrame) -> Column:
    """Rows whose coordinates are all there and finite."""
    ok = F.lit(True)
    for c in RAW:
        ok = ok & F.col(c).isNotNull()
        if dict(df.dtypes)[c] in ("double", "float"):
            ok = ok & ~F.isnan(c) & (F.abs(F.col(c)) < F.lit(float("inf")))
    return ok


def rejects(df: DataFrame) -> DataFrame:
    """Rows that no grid can hold: a coordinate is null, NaN or infinite."""
    return df.where(~F.coalesce(valid(df), F.lit(False)))


def fit_frame(df: DataFrame, policy: Fixed | Span) -> Frame:
    """One pass over three columns; one row comes to the driver."""
    cols = [scaled(c, i) for c, i in zip(RAW, policy.inverse, strict=True)]
    r = df.where(valid(df)).agg(*[f(c) for c in cols for f in (F.min, F.max)], F.count("*")).first()
    v = [x or 0 for x in r]
    return Frame(policy, (v[0], v[2], v[4]), (v[1], v[3], v[5]), v[6])


def apply(df: DataFrame, frame: Frame) -> DataFrame:
    """Adds natural ``x, y, z`` and drops the raw coordinates; rows that can't be placed are left out."""
    out = {}
    for i, (a, c) in enumerate(zip(AXES, RAW, strict=True)):
        v = scaled(c, frame.policy.inverse[i]) - F.lit(frame.low[i])
        if isinstance(frame.policy, Span):
            width = frame.high[i] - frame.low[i]
            v = F.expr("cast(0 as bigint)") if width == 0 else div(v * F.lit(frame.policy.target[i]), F.lit(width))
        out[a] = v
    return df.where(valid(df)).withColumns(out).drop(*RAW)


def div(a: Column, b: Column) -> Column:
    """Integer division of naturals."""
    return F.call_function("div", a, b)


def restore(df: DataFrame, frame: Frame) -> DataFrame:
    """Adds the real coordinates that grid coordinates stand for."""
    out = {}
    for i, (a, c) in enumerate(zip(AXES, RAW, strict=True)):
        v = F.col(a)
        if isinstance(frame.policy, Span):
            v = div(v * F.lit(frame.high[i] - frame.low[i]) + F.lit(frame.policy.target[i] // 2), F.lit(frame.policy.target[i]))
        out[c] = (v + F.lit(frame.low[i])) / F.lit(frame.policy.inverse[i])
    return df.withColumns(out)


def quantization_error(df: DataFrame, frame: Frame) -> DataFrame:
    """The largest distance per axis between a real coordinate and its restored one."""
    kept = df.where(valid(df))
    back = restore(apply(kept.withColumns({f"was_{c}": F.col(c) for c in RAW}), frame), frame)
    return back.agg(*[F.max(F.abs(F.col(f"was_{c}") - F.col(c))).alias(f"error_{a}") for a, c in zip(AXES, RAW, strict=True)])


def to_grid_box(real: tuple[float, ...], frame: Frame) -> Box | None:
    """A closed real box to a closed grid box, clamped to the cloud; None if it holds nothing."""
    low, high = [], []
    for i in range(3):
        a, b, inv = real[i], real[i + 3], frame.policy.inverse[i]
        if isinstance(frame.policy, Span):
            width = max(1, frame.high[i] - frame.low[i])
            lo, hi = math.ceil(a * inv) - frame.low[i], math.floor(b * inv) - frame.low[i]
            t = frame.policy.target[i]
            low.append(-(-max(lo, 0) * t // width) if lo > 0 else 0)
            high.append(hi * t // width)
        else:
            low.append(math.ceil(a * inv) - frame.low[i])
            high.append(math.floor(b * inv) - frame.low[i])
    return clamp((*low, *high), frame.extent)


def clamp(box: Box, extent: tuple[int, int, int]) -> Box | None:
    low = tuple(max(0, v) for v in box[:3])
    high = tuple(min(e, v) for e, v in zip(extent, box[3:], strict=True))
    return None if any(a > b for a, b in zip(low, high, strict=True)) else (*low, *high)
