"""The leaf table: one row per leaf with its box, local coordinates and attribute arrays; native Spark all through."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import TreeConfig
from ..functions.paths import with_box
from .topology import leaf_levels, ordered_index

Box = tuple[int, int, int, int, int, int]


def leaf_points(points: DataFrame, config: TreeConfig, parts: tuple[int, ...], method: str = "window") -> DataFrame:
    """Points with ``leaf`` (its path), ``leaf_level``, box and local coordinates ``lx, ly, lz`` (null at the last level)."""
    p = leaf_levels(points, config, parts, method).withColumn("leaf", F.expr("substring(path, 1, leaf_level)"))
    boxed = with_box(p.withColumnsRenamed({"path": "full", "leaf": "path", "leaf_level": "level"}), parts)
    local = {f"l{a}": F.when(F.col("level") < len(parts), F.col(a) - F.col(f"{a}0")) for a in "xyz"}
    return boxed.withColumns(local)


def in_leaf_order(config: TreeConfig) -> list[str]:
    return ["lx", "ly", "lz", "pid"] if config.leaf_order == "lex" else ["full", "pid"]


def build(points: DataFrame, config: TreeConfig, parts: tuple[int, ...], attributes: tuple[str, ...] = (), method: str = "window") -> DataFrame:
    """``level, path, x0, y0, z0, side, cnt, xs, ys, zs, a_<attribute>, <attribute>_min, <attribute>_max`` per occupied leaf.

    A cell of the last level with more points than a shard should have is several rows of that leaf.
    """
    keep = [*in_leaf_order(config), *[c for c in ("lx", "ly", "lz") if c not in in_leaf_order(config)], *attributes]
    p = leaf_points(points, config, parts, method)
    box = ["level", "path", "x0", "y0", "z0", "side"]
    held = F.sort_array(F.collect_list(F.struct(*keep)))
    rows = p.groupBy(*box, "piece").agg(held.alias("held"), F.count("*").alias("cnt"), *[f(c).alias(f"{c}_{n}") for c in attributes for f, n in ((F.min, "min"), (F.max, "max"))])
    arrays = {n: F.col(f"held.{c}") for n, c in (("xs", "lx"), ("ys", "ly"), ("zs", "lz"))} | {f"a_{c}": F.col(f"held.{c}") for c in attributes}
    return rows.withColumns(arrays).drop("held", "piece")


def overlaps(box: Box) -> Column:
    """Leaves (or shards) whose box meets the query; simple comparisons that reach the scan."""
    cond = F.lit(True)
    for i, a in enumerate("xyz"):
        cond = cond & (F.col(f"{a}0") <= box[i + 3]) & (F.col(f"{a}0") > F.lit(box[i]) - F.col("side"))
    return cond


def explode_points(leaves: DataFrame, attributes: tuple[str, ...] = ()) -> DataFrame:
    """Leaf rows back to points with absolute coordinates."""
    names = ["xs", "ys", "zs", *[f"a_{a}" for a in attributes]]
    p = leaves.select("level", "x0", "y0", "z0", F.explode(F.arrays_zip(*names)).alias("p"))
    return p.select(*[(F.col(f"{a}0") + F.coalesce(F.col(f"p.{a}s"), F.lit(0))).alias(a) for a in "xyz"], *[F.col(f"p.a_{a}").alias(a) for a in attributes])


def within(box: Box) -> Column:
    cond = F.lit(True)
    for i, a in enumerate("xyz"):
        cond = cond & F.col(a).between(box[i], box[i + 3])
    return cond


def points_in_box(leaves: DataFrame, box: Box | None, attributes: tuple[str, ...] = (), where: list[tuple[str, int, int]] = [], value_index: bool = False) -> DataFrame:  # noqa: B006
    """Points of a closed box, with closed ranges of attributes; ``value_index`` skips leaves by their attribute bounds."""
    rows = leaves.where(overlaps(box)) if box else leaves.where(F.lit(False))
    if value_index:
        for a, lo, hi in where:
            rows = rows.where((F.col(f"{a}_max") >= lo) & (F.col(f"{a}_min") <= hi))
    need = tuple(dict.fromkeys([*attributes, *[w[0] for w in where]]))
    p = explode_points(rows, need)
    if box:
        p = p.where(within(box))
    for a, lo, hi in where:
        p = p.where(F.col(a).between(lo, hi))
    return p.select("x", "y", "z", *attributes)


def positions(points: DataFrame, config: TreeConfig, parts: tuple[int, ...], method: str = "window") -> DataFrame:
    """Each point's place in the order of all arrays: leaves breadth first, then the order inside the leaf."""
    p = leaf_points(points, config, parts, method)
    return ordered_index(p, "level", "path", *in_leaf_order(config))


def share_repeats(leaves: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Leaves with equal local coordinates share one payload: (leaf rows with ``payload``, a hash; ``payload, xs, ys, zs``).

    Points of a leaf are in an order of their coordinates, so equal sets of points have equal arrays. Leaves of single
    cells have no coordinates and no payload.
    """
    held = F.when(F.col("xs")[0].isNotNull(), F.sha2(F.to_json(F.arrays_zip("xs", "ys", "zs")), 256))
    rows = leaves.withColumn("payload", held)
    payloads = rows.where("payload is not null").groupBy("payload").agg(*[F.any_value(c).alias(c) for c in ("xs", "ys", "zs")])
    return rows.drop("xs", "ys", "zs"), payloads


def with_payloads(rows: DataFrame, payloads: DataFrame) -> DataFrame:
    """Leaf rows with their coordinates again; cells get a null for each point."""
    none = F.array_repeat(F.lit(None).cast("long"), F.col("cnt").cast("int"))
    joined = rows.join(payloads, "payload", "left")
    return joined.withColumns({c: F.coalesce(c, none) for c in ("xs", "ys", "zs")}).drop("payload")


def leaf_ranges(leaves: DataFrame) -> DataFrame:
    """Half-open range of each leaf's points in the order of all arrays."""
    return ordered_index(leaves.select("level", "path", "cnt"), "level", "path", name="start", first="cnt").select("level", "path", "start", (F.col("start") + F.col("cnt")).alias("stop"))


