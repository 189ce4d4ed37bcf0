"""Queries on a store: shards are pruned by their plain columns, then each is searched on its packed components."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import asdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.paths import with_box
from ..functions.quantize import Box, clamp, restore
from ..sources.store import Store, first_points
from . import leaves
from . import shards as kernel
from .topology import child_boxes

Ranges = Sequence[tuple[str, int, int]]
#: Boxes of a batch up to which they are sent to all tasks; more go through the join of boxes and leaves.
MOST_BOXES = 10_000


def pruned(store: Store, box: Box, where: Ranges = (), value_index: bool = False) -> DataFrame:
    rows = store.shards()
    cond = F.lit(True)
    for i, a in enumerate("xyz"):
        cond = cond & (F.col(f"{a}_min") <= box[i + 3]) & (F.col(f"{a}_max") >= box[i])
    for a, lo, hi in where if value_index else ():
        cond = cond & (F.col(f"{a}_max") >= lo) & (F.col(f"{a}_min") <= hi)
    return rows.where(cond)


def _components(names: Sequence[str]) -> list[str]:
    return ["level", "x0", "y0", "z0", "parts", "leaf_order", "root_leaf", *kernel.FIELDS, *[f"a_{n}" for n in names]]


def _types(columns: Sequence[str]) -> str:
    return "x long, y long, z long" + "".join(f", {c} int" for c in columns)


def _value(v: np.ndarray) -> pa.Array:
    return pa.array(v, pa.int32()) if v.dtype.kind != "f" else pa.array(np.where(np.isnan(v), 0, v).astype(np.int32), pa.int32(), mask=np.isnan(v))


def _relative(box: Box, row: dict) -> Box:
    o = (row["x0"], row["y0"], row["z0"])
    return tuple(v - o[i % 3] for i, v in enumerate(box))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for b in batches:
        for i in range(b.num_rows):  # a shard at a time: its components are the unit of memory
            yield b.slice(i, 1).to_pylist()[0]


def _result(got: dict[str, np.ndarray], row: dict, columns: Sequence[str], extra: dict[str, pa.Array] | None = None) -> pa.RecordBatch:
    arrays = {a: pa.array(got[a] + row[f"{a}0"], pa.int64()) for a in "xyz"} | {c: _value(got[c]) for c in columns}
    arrays = (extra or {}) | arrays
    return pa.RecordBatch.from_arrays(list(arrays.values()), names=list(arrays))


def points_in_box(store: Store, box: Box | None, columns: Sequence[str] = (), early_stop: str = "auto", where: Ranges = (), value_index: bool = False, real: bool = False) -> DataFrame:
    """Points of a closed grid box, in closed attribute ranges if any, with the attributes asked for. No exchange."""
    box = clamp(box, store.frame.extent) if box else None
    if box is None:
        out = store.spark.createDataFrame([], _types(columns))
    else:
        need = list(dict.fromkeys([*columns, *[w[0] for w in where]]))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _rows(batches):
                yield _result(kernel.scan(kernel.from_row(row), _relative(box, row), where, columns, early_stop), row, columns)

        out = pruned(store, box, where, value_index).select(*_components(need)).mapInArrow(run, _types(columns))
    return restore(out, store.frame) if real else out


def points_in_box_where(store: Store, box: Box | None, where: Ranges, columns: Sequence[str] = (), value_index: bool = False) -> DataFrame:
    return points_in_box(store, box, columns, where=where, value_index=value_index)


def points_at(store: Store, x: int, y: int, z: int, columns: Sequence[str] = ()) -> DataFrame:
    return points_in_box(store, (x, y, z, x, y, z), columns)


def scan_all(store: Store, columns: Sequence[str] | None = None) -> DataFrame:
    return points_in_box(store, (0, 0, 0, *store.frame.extent), store.attributes if columns is None else columns)


def slab(store: Store, axis: str, low: int, high: int, columns: Sequence[str] = ()) -> DataFrame:
    """All points between two coordinates of one axis."""
    i, e = "xyz".index(axis), store.frame.extent
    lo, hi = [0, 0, 0], list(e)
    lo[i], hi[i] = low, high
    return points_in_box(store, (*lo, *hi), columns)


def count_in_box(store: Store, box: Box | None) -> DataFrame:
    """One row ``n``: shards that lie fully inside add their count; in others leaves inside do, and only those on the border are opened."""
    box = clamp(box, store.frame.extent) if box else None
    if box is None:
        return store.spark.createDataFrame([(0,)], "n long")
    rows = pruned(store, box)
    inside = F.lit(True)
    for i, a in enumerate("xyz"):
        inside = inside & (F.col(f"{a}_min") >= box[i]) & (F.col(f"{a}_max") <= box[i + 3])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            yield pa.RecordBatch.from_arrays([pa.array(kernel.count(kernel.from_row(row), [_relative(box, row)]))], names=["n"])

    counted = rows.where(inside).select(F.col("cnt").alias("n")).unionByName(rows.where(~inside).select(*_components(())).mapInArrow(run, "n long"))
    return counted.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


def points_in_boxes(store: Store, boxes: DataFrame, where: Ranges = (), columns: Sequence[str] = (), counts: bool = False) -> DataFrame:
    """``q`` with the points of each box of ``boxes(q, xi, yi, zi, xe, ye, ze)``, or with ``n``, their number per shard.

    The boxes, not the payload, go to the tasks; each shard is opened once for all boxes that meet it.
    """
    asked = [tuple(r) for r in boxes.select("q", "xi", "yi", "zi", "xe", "ye", "ze").limit(MOST_BOXES + 1).collect()]
    if len(asked) > MOST_BOXES:
        raise ValueError(f"more than {MOST_BOXES} boxes: join them with the leaf table (surround.join_boxes)")
    shared = store.spark.sparkContext.broadcast(np.array(asked, np.int64).reshape(-1, 7))
    need = list(dict.fromkeys([*columns, *[w[0] for w in where]]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        all_ = shared.value
        for row in _rows(batches):
            low, high = np.array([row[f"{a}_min"] for a in "xyz"]), np.array([row[f"{a}_max"] for a in "xyz"])
            mine = all_[((all_[:, 1:4] <= high) & (all_[:, 4:7] >= low)).all(1)]
            tree = kernel.from_row(row)
            if counts:
                origin = np.array([row[f"{a}0"] for a in "xyz"] * 2)
                yield pa.RecordBatch.from_arrays([pa.array(mine[:, 0]), pa.array(kernel.count(tree, mine[:, 1:] - origin, where))], names=["q", "n"])
                continue
            for q, *box in mine.tolist():
                got = kernel.scan(tree, _relative(tuple(box), row), where, columns)
                if n := len(got["x"]):
                    yield _result(got, row, columns, {"q": pa.array(np.full(n, q))})

    rows = store.shards().select(*_components(need), *[f"{a}_{m}" for a in "xyz" for m in ("min", "max")])
    return rows.mapInArrow(run, "q long, n long" if counts else "q long, " + _types(columns))


def counts_in_boxes(store: Store, boxes: DataFrame, where: Ranges = ()) -> DataFrame:
    """``q, n`` for every box, those without points included."""
    n = points_in_boxes(store, boxes, where, counts=True).groupBy("q").agg(F.sum("n").alias("n"))
    return boxes.select("q").join(n, "q", "left").select("q", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def explain_work(store: Store, box: Box, where: Ranges = (), stop: str = "none") -> DataFrame:
    """What a query looks at: shards, boxes, leaves, points, decoded coordinates, attribute reads; ``stop`` as in ``points_in_box``."""
    box = clamp(box, store.frame.extent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            w = kernel.Work()
            kernel.scan(kernel.from_row(row), _relative(box, row), where, stop=stop, work=w)
            yield pa.RecordBatch.from_pylist([{"shards": 1} | asdict(w)])

    names = ["shards", *asdict(kernel.Work())]
    need = [w[0] for w in where]
    return pruned(store, box, where).select(*_components(need)).mapInArrow(run, ", ".join(f"{n} long" for n in names)).agg(*[F.coalesce(F.sum(n), F.lit(0)).alias(n) for n in names])


def trace_tree(nodes: DataFrame, parts: tuple[int, ...], limit: int, box: Box) -> DataFrame:
    """What a search of the whole tree below its root comes to, from ``nodes(level, path, cnt, kind)``: one row.

    Nodes that don't meet the box go first, so that children are made only of those that do; a child that meets it has such a parent.
    """
    met = with_box(nodes, parts).where(leaves.overlaps(box)).drop("x0", "y0", "z0", "side")
    boxes = with_box(child_boxes(met, parts), parts).where(leaves.overlaps(box))
    split = (F.col("cnt") > limit) & (F.col("level") < len(parts))
    return boxes.agg(F.count("*").alias("boxes_visited"), F.count(F.when(split, 1)).alias("branches"), F.count(F.when(~split & (F.col("cnt") == 0), 1)).alias("empty"), F.count(F.when(~split & (F.col("cnt") > 0), 1)).alias("leaves"))


def point_at(store: Store, position: int) -> DataFrame:
    """One datum by its number in shard order: one shard's row is read, and a few bits of it are looked at."""
    mine = first_points(store).where((F.col("first_point") <= position) & (F.lit(position) < F.col("first_point") + F.col("cnt"))).first()
    columns = store.attributes
    if mine is None:
        return store.spark.createDataFrame([], _types(columns))
    at = position - mine["first_point"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            got = {k: np.array([v]) for k, v in kernel.point_at(kernel.from_row(row), at).items()}
            yield _result(got, row, columns)

    return store.shards().where((F.col("shard") == mine["shard"]) & (F.col("piece") == mine["piece"])).select(*_components(columns)).mapInArrow(run, _types(columns))


def knn(store: Store, x: int, y: int, z: int, k: int) -> DataFrame:
    """The k nearest points: boxes around the target grow until the k-th distance is within half their side."""
    side = max(1, max(store.frame.extent) // 64)
    whole = max(store.frame.extent) * 2 + 1
    while True:
        near = points_in_box(store, (x - side, y - side, z - side, x + side, y + side, z + side))
        d2 = ((F.col("x") - x).cast("decimal(20,0)") * (F.col("x") - x) + (F.col("y") - y).cast("decimal(20,0)") * (F.col("y") - y) + (F.col("z") - z).cast("decimal(20,0)") * (F.col("z") - z)).cast("decimal(38,0)")
        best = near.withColumn("d2", d2).orderBy("d2", "x", "y", "z").limit(k)
        rows = best.collect()  # k rows
        if side >= whole or (len(rows) == k and rows[-1]["d2"] <= side * side):
            return store.spark.createDataFrame([(r["x"], r["y"], r["z"], int(r["d2"])) for r in rows], "x long, y long, z long, d2 long")
        side *= 2
