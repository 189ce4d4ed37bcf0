"""Bit trees of binary matrices in two or three dimensions: boxes are divided until they are empty or single cells."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import sides
from ..functions.quantize import div
from ..sources.shared import cut
from .bitvec import bit_and_rank, bit_blocks
from .topology import classify_nodes, global_bits, level_histogram


def path_of(parts: tuple[int, ...], dims: int):
    s, axes = sides(parts), "xyz"[:dims]
    out = []
    for j, k in enumerate(parts, 1):
        d = F.lit(0)
        for a in axes:
            d = d * k + div(F.col(a), F.lit(s[j])) % k
        out.append(F.char(d + 48))
    return F.concat(*out)


def nodes(cells: DataFrame, parts: tuple[int, ...], dims: int = 2) -> DataFrame:
    """Boxes with cells: ``level, path, cnt, kind``; ``cells`` are distinct coordinates."""
    return classify_nodes(level_histogram(cells.withColumn("path", path_of(parts, dims)), parts), len(parts), 0)


def bits(cells: DataFrame, parts: tuple[int, ...], dims: int = 2) -> DataFrame:
    """``part, pos, bit``: flags of the inner levels (T) and of the last level (L), each breadth first."""
    n = nodes(cells, parts, dims)
    inner = global_bits(n, parts, 0, "branch", dims).select(F.lit("T").alias("part"), "pos", "bit")
    flags = global_bits(n, parts, 0, "occupied", dims)
    # undivided boxes above the last level are empty; what follows them are the last level's cells
    zeros = inner.where("bit = 0").count()
    return inner.unionByName(flags.where(F.col("pos") >= zeros).select(F.lit("L").alias("part"), (F.col("pos") - zeros).alias("pos"), "bit"))


def stored(cells: DataFrame, parts: tuple[int, ...], dims: int = 2) -> DataFrame:
    """The tree as blocks of bits with ranks: T, then L behind it. All levels have the same number of parts."""
    if len(set(parts)) > 1:
        raise ValueError("navigation by rank needs the same parts at every level")
    flags = bits(cells, parts, dims)
    inner = flags.where("part = 'T'").count()
    return cut(bit_blocks(flags.select(F.when(F.col("part") == "T", F.col("pos")).otherwise(F.col("pos") + inner).alias("i"), "bit")))


def _digits(row: dict[str, F.Column], parts: tuple[int, ...], level: int):
    """Which child of its box of level - 1 a place lies in."""
    s, k, d = sides(parts), parts[level - 1], F.lit(0).cast("long")
    for c in row.values():
        d = d * k + div(c, F.lit(s[level])) % k
    return d


def test(cells: DataFrame, probes: DataFrame, parts: tuple[int, ...], dims: int = 2) -> DataFrame:
    """``probes`` with ``is_set``: each goes down the stored bits by rank as long as the flags are set."""
    tree, h, width = stored(cells, parts, dims), len(parts), parts[0] ** dims
    axes = {a: F.col(a) for a in "xyz"[:dims]}
    extent = sides(parts)[0]
    there = F.lit(True)
    for c in axes.values():
        there = there & (c >= 0) & (c < extent)
    p = probes.withColumn("pos", F.when(there, _digits(axes, parts, 1)))
    for level in range(1, h + 1):
        p = bit_and_rank(p, tree, "pos").withColumn("bit", F.coalesce("bit", F.lit(0)))
        if level < h:  # the children of the set bit with number r, from 1, begin at r * width
            p = p.withColumn("pos", F.when(F.col("bit") == 1, F.col("rank") * width + _digits(axes, parts, level + 1))).drop("bit", "rank")
    return p.select(*probes.columns, F.col("bit").cast("int").alias("is_set"))


def report(cells: DataFrame, box: tuple[int, ...], parts: tuple[int, ...], dims: int = 2) -> DataFrame:
    """Set cells of a closed box: from the root, children that meet the box and whose flags are set are followed by rank."""
    axes, s, width = "xyz"[:dims], sides(parts), parts[0] ** dims
    tree = stored(cells, parts, dims)
    row = cells.sparkSession.createDataFrame([(0, *[0] * dims)], "rank long, " + ", ".join(f"{a} long" for a in axes))
    for level, k in enumerate(parts, 1):
        child = row.withColumn("digit", F.explode(F.sequence(F.lit(0), F.lit(width - 1)))).withColumn("pos", F.col("rank") * width + F.col("digit"))
        for i, a in enumerate(axes):
            low = F.col(a) + div(F.col("digit"), F.lit(k ** (dims - 1 - i))) % k * s[level]
            child = child.withColumn(a, low).where((F.col(a) <= box[i + dims]) & (F.col(a) + s[level] - 1 >= box[i]))
        row = bit_and_rank(child, tree, "pos").where("bit = 1").select("rank", *axes)
    return row.select(*axes)
