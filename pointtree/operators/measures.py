"""Space, work and descriptions of clouds. Time is measured on the driver around a write that keeps nothing."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from statistics import mean, median

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.store import Store
from . import shards as kernel
from .baselines import RECORD, Blocks, _sums, count_each
from .shards import FIELDS

MIB = 1 << 20


def raw_space(points: DataFrame) -> DataFrame:
    """``points, bytes, mb``: 20 bytes a point, in MiB rounded up."""
    n = points.agg(F.count("*").alias("points"))
    size = F.col("points") * RECORD.itemsize
    return n.select("points", size.alias("bytes"), F.ceil(size / MIB).alias("mb"))


def space(store: Store) -> DataFrame:
    """Bytes and bits per point of every component."""
    names = [*FIELDS, *[f"a_{a}" for a in store.attributes]]
    sums = store.shards().agg(F.sum("cnt").alias("points"), *[F.sum(F.octet_length(n)).cast("long").alias(n) for n in names])
    rows = sums.select("points", F.explode(F.map_from_arrays(F.array(*map(F.lit, names)), F.array(*names))).alias("component", "bytes"))
    return rows.select("component", "bytes", (F.col("bytes") * 8 / F.col("points")).alias("bits_per_point"))


def block_space(b: Blocks) -> DataFrame:
    names = ["x", "y", "z", *b.attributes]
    sums = b.blocks().agg(*[F.sum(F.octet_length(f"d_{n}")).cast("long").alias(n) for n in names])
    return sums.select(F.explode(F.map_from_arrays(F.array(*map(F.lit, names)), F.array(*names))).alias("component", "bytes"))


def saving(a: float, b: float) -> float:
    """By how many per cent a is smaller than b."""
    return 100 * (1 - a / b) if b else 0.0


def time_queries(run: Callable[[object], DataFrame], boxes: Sequence[object], warmup: int = 1, repeat: int = 5) -> dict[str, float]:
    """Mean and median ms a box; each run is written to nowhere."""
    for b in boxes[:warmup]:
        run(b).write.format("noop").mode("overwrite").save()
    taken = []
    for _ in range(repeat):
        for b in boxes:
            began = time.perf_counter()
            run(b).write.format("noop").mode("overwrite").save()
            taken.append(1000 * (time.perf_counter() - began))
    return {"mean_ms": mean(taken), "median_ms": median(taken), "queries": len(taken)}


def speedup(slow_ms: float, fast_ms: float) -> float:
    """How many times as long the slower one takes."""
    return slow_ms / fast_ms if fast_ms else 0.0


#: Bytes of components, blocks or records that ``in_one_process`` brings to the driver at most.
MOST_LOCAL = 1 << 30


def _local(rows: DataFrame, size: str) -> list[dict]:
    total = rows.agg(F.sum(F.expr(size))).first()[0] or 0
    if total > MOST_LOCAL:
        raise ValueError(f"{total} bytes are too many for one process")
    return [r.asDict() for r in rows.collect()]


def in_one_process(store: Store, blocks: Blocks, raw: str, boxes: Sequence[tuple[int, ...]], where: Sequence[tuple[str, int, int]] = ()) -> dict[str, dict[str, float]]:
    """Mean ms a box of each format in one process, from memory, without jobs: what the published times measure.

    Only for clouds of a bounded size, which is checked. Each box gives the same count in every format, or this fails.
    """
    names = list(dict.fromkeys(w[0] for w in where))
    columns = ["x0", "y0", "z0", "parts", "leaf_order", "root_leaf", *FIELDS, *[f"a_{n}" for n in names], *[f"{a}_{m}" for a in "xyz" for m in ("min", "max")]]
    binary = [*FIELDS, *[f"a_{n}" for n in names]]
    shards = _local(store.shards().select(*columns), "+".join(f"octet_length({c})" for c in binary))
    low, high = (np.array([[r[f"{a}_{m}"] for a in "xyz"] for r in shards]) for m in ("min", "max"))
    trees = [kernel.from_row(r) for r in shards]
    held = {r["block"]: r for r in _local(blocks.blocks().select("block", *[f"d_{n}" for n in ("x", "y", "z", *names)]), "+".join(f"octet_length(d_{n})" for n in ("x", "y", "z", *names)))}
    cells = _local(blocks.cells(), "8 * size(blocks)")
    runs = [bytes(r["records"]) for r in _local(store.spark.read.parquet(raw), "octet_length(records)")]

    def octree(box: tuple[int, ...]) -> int:
        met = np.flatnonzero((low <= box[3:]).all(1) & (high >= box[:3]).all(1))
        n = 0
        for k in met:
            o = [shards[k][f"{a}0"] for a in "xyz"]
            n += len(kernel.scan(trees[k], tuple(v - o[i % 3] for i, v in enumerate(box)), where)["_position"])
        return n

    def block(box: tuple[int, ...]) -> int:
        n = 0
        for b in {b for c in cells if c["x_min"] <= box[3] and c["x_max"] >= box[0] and c["y_min"] <= box[4] and c["y_max"] >= box[1] for b in c["blocks"]}:
            got = {a: _sums(held[b][f"d_{a}"]) for a in ("x", "y", "z", *names)}
            n += int(count_each(np.array([[0, *box]]), got, where)[1].sum())
        return n

    def records(box: tuple[int, ...]) -> int:
        n = 0
        for r in runs:
            r = np.frombuffer(r, RECORD)
            n += int(count_each(np.array([[0, *box]]), {a: r[a].astype(np.int64) for a in ("x", "y", "z", *names)}, where)[1].sum())
        return n

    out: dict[str, dict[str, float]] = {}
    want = None
    for name, run in (("octree", octree), ("block", block), ("raw", records)):
        run(boxes[0])
        began = time.perf_counter()
        got = [run(tuple(b)) for b in boxes]
        out[name] = {"mean_ms": round(1000 * (time.perf_counter() - began) / len(boxes), 3), "queries": len(boxes), "failed": sum(g == 0 and w > 0 for g, w in zip(got, want or got, strict=True))}
        if want is not None and got != want:
            raise AssertionError(f"{name} gives other counts")
        want = got
    for name in ("block", "raw"):
        out[name]["octree_speedup"] = round(speedup(out[name]["mean_ms"], out["octree"]["mean_ms"]), 2)
    return out


def failures(got: DataFrame, want: DataFrame) -> DataFrame:
    """``queries_run, queries_failed, queries_timed``: a query fails that finds nothing where there is something."""
    j = want.withColumnRenamed("n", "want").join(got, "q", "left")
    failed = ((F.col("want") > 0) & (F.coalesce("n", F.lit(0)) == 0)).cast("long")
    return j.agg(F.count("*").alias("queries_run"), F.coalesce(F.sum(failed), F.lit(0)).alias("queries_failed"), (F.count("*") - F.coalesce(F.sum(failed), F.lit(0))).alias("queries_timed"))


def describe_cloud(raw: DataFrame, gridded: DataFrame, inverse: Sequence[int] = (1, 1, 1)) -> DataFrame:
    """``points``, real bounds in units of the inverse scale (``low_x`` to ``high_z``), and the largest converted coordinates."""
    unit = lambda f, a, k: F.round(f(f"r{a}") * k).cast("long")
    real = raw.agg(*[unit(f, a, k).alias(f"{n}_{a}") for a, k in zip("xyz", inverse, strict=True) for n, f in (("low", F.min), ("high", F.max))])
    return gridded.agg(F.count("*").alias("points"), *[F.max(a).alias(f"max_{a}") for a in "xyz"]).crossJoin(real)  # one row each


def density(points: DataFrame, side: int) -> DataFrame:
    """Points per square cell of the ground plan."""
    cell = lambda a: F.call_function("div", F.col(a), F.lit(side)).alias(f"c{a}")
    return points.groupBy(cell("x"), cell("y")).agg(F.count("*").alias("n"))
