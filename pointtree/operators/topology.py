"""The boxes of a thresholded octree: counts, kinds, leaf levels, shards and the bits of the whole tree.

A box is divided if it holds more points than the leaf limit and has a side above 1; the root always is. Counts are taken
once at the finest level that is asked for and rolled up, so that only the first aggregate sees points. Points come to
their boxes in one pass more, by equality of prefixes of their paths.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StringType, StructField, StructType

from ..config import TreeConfig
from ..functions.paths import common_levels, path_of, prefix_of
from ..sources.shared import cut
from . import shards as kernel

#: Rows of a plan of boxes up to which it is broadcast (some 60 bytes each).
BROADCAST_BOXES = 500_000
#: Levels of a first look at points whose number is not known, and of any look (64 boxes a point of a plane, 2**21 in all at most).
FIRST_LEVELS, MOST_LEVELS = 4, 7


def with_paths(points: DataFrame, parts: tuple[int, ...]) -> DataFrame:
    return points if "path" in points.columns else points.withColumn("path", path_of(parts))


def level_histogram(points: DataFrame, parts: tuple[int, ...], levels: int | None = None, first: int = 1) -> DataFrame:
    """``level, path, cnt`` of all boxes that hold points, for levels first..levels."""
    levels = len(parts) if levels is None else levels
    finest = with_paths(points, parts).groupBy(F.substring("path", 1, levels).alias("path")).agg(F.count("*").alias("cnt"))
    rows = finest.select(F.explode(F.sequence(F.lit(first), F.lit(levels))).alias("level"), F.col("path").alias("full"), "cnt")
    return rows.groupBy("level", F.expr("substring(full, 1, level)").alias("path")).agg(F.sum("cnt").alias("cnt"))


def classify_nodes(histogram: DataFrame, height: int, limit: int) -> DataFrame:
    """The tree's own boxes with points: ``kind`` is branch, leaf, or cell for undivided boxes of the last level."""
    heavy = (F.col("cnt") > limit) & (F.col("level") < height)
    kind = F.when(F.col("level") == height, "cell").when(heavy, "branch").otherwise("leaf")
    parents = histogram.where(heavy).select((F.col("level") + 1).alias("level"), F.col("path").alias("parent"))
    below = histogram.where("level > 1").withColumn("parent", F.expr("substring(path, 1, level - 1)")).join(parents, ["level", "parent"], "left_semi")
    return histogram.where("level = 1").select("level", "path", "cnt").unionByName(below.select("level", "path", "cnt")).withColumn("kind", kind)


@dataclass(frozen=True)
class Boxes:
    """The coarsest boxes of up to ``most`` points, found in rounds that each look ``depth`` levels deep.

    A round's ``cells(cell, level, cnt)`` has every occupied cell of its depth below the boxes that were too heavy
    before, with the level and the points of the box it belongs to; both are null where that is too heavy still.
    """

    rounds: tuple[tuple[int, DataFrame], ...]
    parts: tuple[int, ...]
    most: int

    def boxes(self) -> DataFrame:
        """``level, path, cnt`` of the boxes, one row each."""
        found = [c.where("level is not null").select("level", F.expr("substring(cell, 1, level)").alias("path"), "cnt").distinct() for _, c in self.rounds]
        return reduce(DataFrame.unionByName, found)

    def beside(self, points: DataFrame, name: str) -> DataFrame:
        """Points with ``name``, the path of their box, ``<name>_level`` and ``piece``, in one pass over the points.

        Boxes don't overlap, so each round is one equality join by the prefix of its depth. A single cell with more
        points than a box should have is dealt to pieces by pid; elsewhere ``piece`` is 0.
        """
        level, box, cnt, held = [], [], [], []
        for i, (depth, cells) in enumerate(self.rounds):
            own = cells.where("level is not null").select(F.col("cell").alias(f"cell{i}"), F.col("level").alias(f"level{i}"), F.col("cnt").alias(f"cnt{i}"))
            own = F.broadcast(own) if own.count() <= BROADCAST_BOXES else own
            points = points.withColumn(f"cell{i}", prefix_of(self.parts, depth)).join(own, f"cell{i}", "left")
            level.append(F.col(f"level{i}"))
            cnt.append(F.when(level[-1].isNotNull(), F.col(f"cnt{i}")))
            box.append(F.when(level[-1].isNotNull(), F.expr(f"substring(cell{i}, 1, level{i})")))
            held += [f"cell{i}", f"level{i}", f"cnt{i}"]
        pieces = F.ceil(F.coalesce(*cnt) / self.most)
        piece = F.when((F.coalesce(*level) == len(self.parts)) & (pieces > 1), F.pmod(F.xxhash64("pid"), pieces)).otherwise(0) if "pid" in points.columns else F.lit(0)
        return points.withColumns({name: F.coalesce(*box), f"{name}_level": F.coalesce(*level), "piece": piece.cast("int")}).drop(*held)


def plan_boxes(points: DataFrame, parts: tuple[int, ...], most: int, divide_root: bool = False, step: int | None = None, count: int | None = None) -> Boxes:
    """Finds the coarsest boxes of up to ``most`` points, or single cells.

    A round is one aggregate of points, at a depth that should be enough for the heaviest box left (``step`` fixes it);
    coarser counts are rolled up from that, and the next round looks below the heavy cells only. The whole cloud is one
    box, of level 0, if it is light enough and the root need not be divided.
    """
    h, bits = len(parts), [2 * (k.bit_length() - 1) for k in parts]
    xyz = points.select(*[c for c in ("x", "y", "z", "path") if c in points.columns])
    depth, heaviest, rounds, live = 0, count, [], xyz
    while True:
        deeper, gain = depth, 1
        # as if points filled a plane: cells of volumes are fewer points each, and a heavy box is looked at again
        while deeper < h and ((deeper - depth < step) if step else deeper == depth or (gain * most < 4 * heaviest if heaviest else deeper - depth < FIRST_LEVELS)) and (step or deeper - depth < MOST_LEVELS):
            gain <<= bits[deeper]
            deeper += 1
        cells = cut(live.groupBy(prefix_of(parts, deeper, "path" in live.columns).alias("cell")).agg(F.count("*").alias("n")))
        if not rounds:
            total = cells.agg(F.sum("n")).first()[0] or 0
            if not total or total <= most and not divide_root:
                return Boxes(((0, points.sparkSession.createDataFrame([("", 0, total)] if total else [], "cell string, level int, cnt long")),), parts, most)
        each = cells.select("cell", "n", F.explode(F.sequence(F.lit(depth + 1), F.lit(deeper))).alias("level")).withColumn("path", F.expr("substring(cell, 1, level)"))
        nodes = each.groupBy("level", "path").agg(F.sum("n").alias("cnt")).where((F.col("cnt") <= most) | (F.col("level") == h))
        best = each.join(nodes, ["level", "path"]).groupBy("cell").agg(F.min(F.struct("level", "cnt")).alias("box"))
        found = cut(cells.join(best, "cell", "left").select("cell", "n", F.col("box.level").alias("level"), F.col("box.cnt").alias("cnt")))
        rounds.append((deeper, found.select("cell", "level", "cnt")))
        heavy = found.where("level is null")
        n, heaviest = heavy.agg(F.count("*"), F.max("n")).first()
        if not n:
            return Boxes(tuple(rounds), parts, most)
        depth = deeper
        over = heavy.select(F.col("cell").alias("over"))
        live = xyz.join(F.broadcast(over) if n <= BROADCAST_BOXES else over, prefix_of(parts, depth, "path" in xyz.columns) == F.col("over"), "left_semi")


def frontier(points: DataFrame, parts: tuple[int, ...], most: int, divide_root: bool = False) -> DataFrame:
    """The coarsest boxes of up to ``most`` points, or single cells: ``level, path, cnt``."""
    return plan_boxes(points, parts, most, divide_root).boxes()


def tree_boxes(points: DataFrame, parts: tuple[int, ...], limit: int, shard_points: int = 200_000, count: int | None = None) -> DataFrame:
    """The tree's own boxes with points, as ``classify_nodes`` gives them: ``level, path, cnt, kind``.

    Boxes of up to ``shard_points`` points are found first; their points come to one task each, in one exchange, and what
    lies below is counted there. Only boxes above are added up by Spark. A level that the tree does not reach is not counted.
    """
    h = len(parts)
    xyz = points.select("x", "y", "z")
    plan = plan_boxes(xyz, parts, max(shard_points, limit), True, count=count)
    above = plan.boxes().where("level > 0").select(F.explode(F.sequence(F.lit(1), "level")).alias("level"), F.col("path").alias("full"), "cnt")
    above = cut(above.groupBy("level", F.expr("substring(full, 1, level)").alias("path")).agg(F.sum("cnt").alias("cnt")))

    def run(key: tuple, t: pa.Table) -> pa.Table:
        x, y, z = (t.column(a).to_numpy() for a in "xyz")
        _, boxes = kernel.divide(x, y, z, parts, key[1].as_py(), limit)
        made = [pa.table({"level": pa.array(np.full(len(n), level, np.int32)), "path": kernel.paths(x[at], y[at], z[at], parts, level), "cnt": pa.array(n.astype(np.int64))}) for level, at, n in boxes]
        return pa.concat_tables(made) if made else pa.table({"level": pa.array([], pa.int32()), "path": pa.array([], pa.string()), "cnt": pa.array([], pa.int64())})

    placed = plan.beside(xyz, "shard").where(F.col("shard_level") < h)  # a cell of the last level has nothing below
    below = placed.groupBy("shard", "shard_level").applyInArrow(run, "level int, path string, cnt long")
    kind = F.when(F.col("level") == h, "cell").when(F.col("cnt") > limit, "branch").otherwise("leaf")
    return above.unionByName(below).withColumn("kind", kind)


def _leaf_levels_by(points: DataFrame, parts: tuple[int, ...], limit: int, shard_points: int, levels_of: Callable[..., np.ndarray]) -> DataFrame:
    """Adds ``path``, ``leaf_level`` and ``piece``: shards as for the sort, each given to ``levels_of(x, y, z, level)`` in one task."""
    given = "path" in points.columns
    placed = plan_boxes(points, parts, max(shard_points, limit), True).beside(points, "shard")
    columns = points.columns + ([] if given else ["path"])

    def run(key: tuple, t: pa.Table) -> pa.Table:
        x, y, z = (t.column(a).to_numpy() for a in "xyz")
        if not given:
            t = t.append_column("path", kernel.paths(x, y, z, parts, len(parts)))
        leaf = levels_of(x, y, z, key[1].as_py())
        return t.select([*columns, "piece"]).append_column("leaf_level", pa.array(leaf, pa.int32()))

    types = StructType([*placed.select(*points.columns).schema, *([] if given else [StructField("path", StringType())]), StructField("piece", IntegerType()), StructField("leaf_level", IntegerType())])
    return placed.groupBy("shard", "shard_level", "piece").applyInArrow(run, types)


def leaf_levels_histogram(points: DataFrame, parts: tuple[int, ...], limit: int, shard_points: int = 2_000_000) -> DataFrame:
    """Adds ``path``, ``leaf_level`` and ``piece``: one count of single cells serves all levels of a shard."""
    return _leaf_levels_by(points, parts, limit, shard_points, lambda x, y, z, level: kernel.count_up(x, y, z, parts, level, limit))


def leaf_levels_iterative(points: DataFrame, parts: tuple[int, ...], limit: int, step: int = 3, shard_points: int = 2_000_000) -> DataFrame:
    """Adds ``path``, ``leaf_level`` and ``piece`` by refinement of each shard: only points of boxes that are too heavy still stay for the next round."""
    return _leaf_levels_by(points, parts, limit, shard_points, lambda x, y, z, level: kernel.divide(x, y, z, parts, level, limit, step)[0])


def assign_shards(points: DataFrame, parts: tuple[int, ...], most: int, count: int | None = None) -> DataFrame:
    """Adds ``shard`` (the path of its box), ``shard_level`` and ``piece``: up to ``most`` points share all three."""
    return plan_boxes(points, parts, most, count=count).beside(points, "shard")


def leaf_levels_window(points: DataFrame, parts: tuple[int, ...], limit: int, shard_points: int = 2_000_000) -> DataFrame:
    """Adds ``path``, ``leaf_level`` and ``piece`` in one sort by path.

    A box is heavy if and only if some run of limit + 1 neighbours in path order lies in it whole. A point's leaf is thus one
    level below the deepest box that such a run with the point shares. Sorts are per shard, a frontier box of bounded size.
    """
    h = len(parts)
    pts = with_paths(assign_shards(points, parts, max(shard_points, limit + 1)), parts)
    order = Window.partitionBy("shard", "piece").orderBy("path", "pid")
    ahead = [F.lead(a, limit).over(order) for a in "xyz"]
    shared = pts.withColumns({f"far_{a}": c for a, c in zip("xyz", ahead, strict=True)})
    run = F.when(F.col("far_x").isNotNull(), common_levels(tuple(map(F.col, "xyz")), (F.col("far_x"), F.col("far_y"), F.col("far_z")), parts))
    deepest = F.max("run").over(order.rowsBetween(-limit, 0))
    level = F.least(F.lit(h), F.greatest(F.coalesce("deepest", F.lit(-1)) + 1, F.col("shard_level"), F.lit(1)))
    return shared.withColumn("run", run).withColumn("deepest", deepest).withColumn("leaf_level", level.cast("int")).drop("far_x", "far_y", "far_z", "run", "deepest", "shard", "shard_level")


def leaf_levels(points: DataFrame, config: TreeConfig, parts: tuple[int, ...], method: str = "window") -> DataFrame:
    ways = {"window": lambda: leaf_levels_window(points, parts, config.leaf_limit, config.shard_points), "iterative": lambda: leaf_levels_iterative(points, parts, config.leaf_limit, shard_points=config.shard_points), "histogram": lambda: leaf_levels_histogram(points, parts, config.leaf_limit, config.shard_points)}
    return ways[method]()


def ordered_index(rows: DataFrame, *keys: str, name: str = "pos", first: str | None = None) -> DataFrame:
    """Adds the place of each row in the order of ``keys``, or the sum of ``first`` over the rows before it.

    Ranges are sorted apart; what each range adds up to is summed over ranges, one row each.
    """
    weight = F.col(first) if first else F.lit(1).cast("long")
    placed = cut(rows.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("range_no", F.spark_partition_id()).withColumn("in_range", F.monotonically_increasing_id()).withColumn("range_add", weight))
    sums = placed.groupBy("range_no").agg(F.sum("range_add").alias("add"))
    before = sums.select("range_no", F.coalesce(F.sum("add").over(Window.orderBy("range_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.coalesce(F.sum("range_add").over(Window.partitionBy("range_no").orderBy("in_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return placed.withColumn("inside", inside).join(F.broadcast(before), "range_no").withColumn(name, F.col("before") + F.col("inside")).drop("range_no", "in_range", "range_add", "before", "inside")


def child_boxes(nodes: DataFrame, parts: tuple[int, ...], dims: int = 3) -> DataFrame:
    """All children of divided boxes, empty ones with count 0: ``level, path, cnt``. The root is divided always."""
    spark, h = nodes.sparkSession, len(parts)
    root = spark.createDataFrame([(0, "")], "level int, path string")
    divided = root.unionByName(nodes.where("kind = 'branch'").select("level", "path"))
    width = F.element_at(F.array(*[F.lit(k**dims) for k in parts]), F.col("level") + 1)
    children = divided.where(F.col("level") < h).select((F.col("level") + 1).alias("level"), F.explode(F.sequence(F.lit(0), width - 1)).alias("d"), F.col("path").alias("parent")).select("level", F.concat("parent", F.char(F.col("d") + 48)).alias("path"))
    return children.join(nodes.select("level", "path", "cnt"), ["level", "path"], "left").withColumn("cnt", F.coalesce("cnt", F.lit(0).cast("long")))


def global_bits(nodes: DataFrame, parts: tuple[int, ...], limit: int, which: str, dims: int = 3) -> DataFrame:
    """``pos, bit`` of the whole tree in breadth-first order: ``branch``, ``occupied`` or ``tally`` flags."""
    h = len(parts)
    if which == "tally":
        leaves = ordered_index(nodes.where("kind <> 'branch'").select("level", "path", "cnt"), "level", "path", name="start", first="cnt")
        return leaves.select(F.explode(F.sequence(F.lit(0).cast("long"), F.col("cnt") - 1)).alias("i"), "start", "cnt").select((F.col("start") + F.col("i")).alias("pos"), (F.col("i") == F.col("cnt") - 1).cast("int").alias("bit"))
    boxes = child_boxes(nodes, parts, dims)
    divided = (F.col("cnt") > limit) & (F.col("level") < h)
    if which == "branch":
        return ordered_index(boxes.where(F.col("level") < h).withColumn("bit", divided.cast("int")), "level", "path").select("pos", "bit")
    return ordered_index(boxes.where(~divided).withColumn("bit", (F.col("cnt") > 0).cast("int")), "level", "path").select("pos", "bit")
