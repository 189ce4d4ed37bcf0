"""The store: one Parquet row per shard with the components of its sub-octree, and a manifest.

Rows carry what pruning needs as plain columns (box, bounds of points and attributes); components are binary columns of
their own, so that a query reads only those it touches. A folder holds ``shards`` and ``manifest``.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import TreeConfig, sides
from ..functions.quantize import Fixed, Frame, Span
from ..operators import shards as kernel
from ..operators.topology import assign_shards
from .shared import shared_dir


@dataclass(frozen=True)
class Store:
    spark: SparkSession
    path: str
    parts: tuple[int, ...]
    config: TreeConfig
    frame: Frame
    attributes: tuple[str, ...]

    def shards(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/shards")


def _schema(attributes: tuple[str, ...]) -> str:
    plain = "shard string, piece int, level int, x0 long, y0 long, z0 long, side long, cnt long, " + ", ".join(f"{a}_{m} long" for a in "xyz" for m in ("min", "max"))
    bounds = "".join(f", {a}_{m} double" for a in attributes for m in ("min", "max"))
    return plain + bounds + ", parts array<int>, leaf_order string, root_leaf boolean, " + ", ".join(f"{f} binary" for f in kernel.FIELDS) + "".join(f", a_{a} binary" for a in attributes)


def _pack(config: TreeConfig, parts: tuple[int, ...], attributes: tuple[str, ...], schema: pa.Schema):
    s = sides(parts)

    def run(key: tuple, t: pa.Table) -> pa.Table:
        shard, level, piece = key[0].as_py(), key[1].as_py(), key[2].as_py()
        c = {a: t.column(a).to_numpy() for a in "xyz"}
        origin, side = [], s[level]
        for i, a in enumerate("xyz"):
            at = 0
            for j, digit in enumerate(shard, 1):
                k, d = parts[j - 1], ord(digit) - 48
                at += (d // (k * k), d // k % k, d % k)[i] * s[j]
            origin.append(at)
        held = {a: t.column(a).cast(pa.float64()).fill_null(float("nan")).to_numpy() if t.column(a).null_count else t.column(a).cast(pa.int64()).to_numpy() for a in attributes}
        leaf = level > 0 and (t.num_rows <= config.leaf_limit or level == len(parts))
        tree = kernel.pack(*(c[a] - o for a, o in zip("xyz", origin, strict=True)), t.column("pid").to_numpy(), held, parts[level:], config.leaf_limit, config.leaf_order, leaf)
        row: dict[str, Any] = {"shard": shard, "piece": piece, "level": level, "side": side, "cnt": t.num_rows} | dict(zip(("x0", "y0", "z0"), origin, strict=True)) | {f"{a}_{m}": f(c[a]).item() for a in "xyz" for m, f in (("min", np.min), ("max", np.max))}
        for a, v in held.items():
            some = v[~np.isnan(v)] if v.dtype.kind == "f" else v
            row |= {f"{a}_min": float(some.min()) if len(some) else None, f"{a}_max": float(some.max()) if len(some) else None}
        return pa.Table.from_pylist([row | kernel.to_row(tree)], schema=schema)

    return run


def build(points: DataFrame, frame: Frame, config: TreeConfig, attributes: tuple[str, ...] = (), path: str | None = None) -> Store:
    """Write a store of gridded ``points(pid, x, y, z, attributes)``: one wide exchange, a shard to a task at a time.

    A cell of the last level with more points than a shard should have becomes several shards of that cell.
    """
    spark, parts = points.sparkSession, frame.parts(config)
    path = path or f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    schema = _schema(attributes)
    placed = assign_shards(points.select("pid", "x", "y", "z", *attributes), parts, config.shard_points, frame.count)
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    packed = placed.groupBy("shard", "shard_level", "piece").applyInArrow(_pack(config, parts, attributes, to_arrow_schema(StructType.fromDDL(schema))), schema)
    packed.write.parquet(f"{path}/shards")
    policy, kind = frame.policy, "span" if isinstance(frame.policy, Span) else "fixed"
    row = (kind, list(policy.target) if kind == "span" else [], list(policy.inverse), list(frame.low), list(frame.high), frame.count, list(parts), config.fanout, config.leaf_limit, config.leaf_order, config.shard_points, list(attributes))
    spark.createDataFrame([row], "policy string, target array<long>, inverse array<long>, low array<long>, high array<long>, points long, parts array<int>, fanout int, leaf_limit int, leaf_order string, shard_points long, attributes array<string>").coalesce(1).write.parquet(f"{path}/manifest")
    return open_store(spark, path)


def open_store(spark: SparkSession, path: str) -> Store:
    m = spark.read.parquet(f"{path}/manifest").first()
    inverse = tuple(m["inverse"])
    policy = Span(tuple(m["target"]), inverse) if m["policy"] == "span" else Fixed(inverse)
    config = TreeConfig(fanout=m["fanout"], leaf_limit=m["leaf_limit"], leaf_order=m["leaf_order"], shard_points=m["shard_points"])
    return Store(spark, path, tuple(m["parts"]), config, Frame(policy, tuple(m["low"]), tuple(m["high"]), m["points"]), tuple(m["attributes"]))


def first_points(store: Store) -> DataFrame:
    """Each shard with the number of points before it in path order; a row a shard, none of a point."""
    return store.shards().select("shard", "piece", "cnt", F.coalesce(F.sum("cnt").over(Window.orderBy("shard", "piece").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first_point"))
