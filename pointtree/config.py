"""Parameters of a thresholded octree."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class AttributeSpec:
    """An attribute column: how it is stored (``mlv``, ``bit`` or ``auto``: a bit if no value exceeds 1)."""

    name: str
    encoding: str = "auto"


@dataclass(frozen=True)
class TreeConfig:
    """``fanout`` parts per axis at every level, or a ``schedule`` of them from the top; boxes of up to ``leaf_limit`` points stay whole."""

    fanout: int = 2
    schedule: tuple[int, ...] = ()
    leaf_limit: int = 100
    leaf_order: str = "zorder"  # or "lex"
    early_stop: str = "auto"  # "code", "x" or "none"; auto suits the order
    shard_points: int = 2_000_000
    attributes: tuple[AttributeSpec, ...] = field(default=())

    def __post_init__(self) -> None:
        if any(k < 2 or k > 4 or k & (k - 1) for k in (self.fanout, *self.schedule)):
            raise ValueError("parts per axis are 2 or 4")
        if self.leaf_limit < 1 or self.leaf_order not in ("zorder", "lex"):
            raise ValueError("leaf_limit is 1 or more, leaf_order zorder or lex")

    def parts(self, most: int) -> tuple[int, ...]:
        """Parts per axis of each level for coordinates 0..most: the schedule, then the fanout as long as needed."""
        out, side, given = [], 1, list(self.schedule)
        while side <= most or not out:
            out.append(given.pop(0) if given else self.fanout)
            side *= out[-1]
        return tuple(out)


def sides(parts: tuple[int, ...]) -> list[int]:
    """Side of the boxes of levels 0..h."""
    out = [1]
    for k in reversed(parts):
        out.append(out[-1] * k)
    return out[::-1]
