"""Where queries are registered with their SQL counterparts, and SQL pieces that several of them share."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import TreeConfig
from ..functions.quantize import Frame, fit_frame
from ..operators import leaves as leaf_table
from ..operators import topology
from ..sources import clouds
from ..sources import store as stores
from ..sources.shared import cut

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_built: dict[tuple, object] = {}


def query(name: str, sql: str | None = None):
    def register(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def once(spark: SparkSession, key: tuple, make: Callable[[], object]) -> object:
    """What one application builds once for several queries (stores are files)."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _built:
        _built[full] = make()
    return _built[full]


def cloud(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, Frame]:
    """The cloud on its natural grid, and its frame. Frames are fitted once; clouds of the same points and policy share the pass."""
    c = clouds.CLOUDS[name]
    whole = once(spark, ("frame", sf_dir, c.load, c.policy), lambda: fit_frame(clouds.load(spark, sf_dir, name), c.policy))
    points = clouds.on_grid(spark, sf_dir, name, whole)
    return points, whole if c.tiles is None else once(spark, ("tiles", sf_dir, name), lambda: replace(whole, count=points.count()))


def together(spark: SparkSession, sf_dir: str, names: Sequence[str]) -> tuple[DataFrame, dict[str, Frame]]:
    """Clouds of one table and policy, from one pass: points on their grid with ``tile``, written once, and each cloud's frame."""
    c = clouds.CLOUDS[names[0]]
    whole = once(spark, ("frame", sf_dir, c.load, c.policy), lambda: fit_frame(clouds.load(spark, sf_dir, names[0]), c.policy))
    points = cut(clouds.tiled(spark, sf_dir, names[0], whole).select("pid", "x", "y", "z", *c.attributes, "tile"))
    counts = {r["tile"]: r["n"] for r in points.groupBy("tile").agg(F.count("*").alias("n")).collect()}  # a row a tile
    frames = {n: once(spark, ("tiles", sf_dir, n), lambda t=clouds.CLOUDS[n].tiles: replace(whole, count=sum(k for i, k in counts.items() if t is None or i < t))) for n in names}
    return points, frames


CONFIG = TreeConfig(shard_points=20_000)


def store_of(spark: SparkSession, sf_dir: str, name: str, config: TreeConfig = CONFIG) -> stores.Store:
    def make() -> stores.Store:
        points, frame = cloud(spark, sf_dir, name)
        return stores.build(points, frame, config, clouds.CLOUDS[name].attributes)

    return once(spark, ("store", sf_dir, name, config), make)


def leaves_of(spark: SparkSession, sf_dir: str, name: str, config: TreeConfig = CONFIG) -> tuple[DataFrame, Frame]:
    def make() -> tuple[DataFrame, Frame]:
        points, frame = cloud(spark, sf_dir, name)
        return cut(leaf_table.build(points, config, frame.parts(config), clouds.CLOUDS[name].attributes)), frame

    return once(spark, ("leaves", sf_dir, name, config), make)


def nodes_of(spark: SparkSession, sf_dir: str, name: str, config: TreeConfig = CONFIG) -> tuple[DataFrame, Frame]:
    points, frame = cloud(spark, sf_dir, name)
    parts = frame.parts(config)
    return topology.tree_boxes(points, parts, config.leaf_limit, count=frame.count), frame


def sql_points(name: str, k: int = 2, alias: str = "pts") -> str:
    """CTEs: the gridded cloud with ``path`` and height ``h``."""
    b = k.bit_length() - 1
    digit = " + ".join(f"{w} * ((%s >> ({b} * j)) & {k - 1})" % a for a, w in zip("xyz", (k * k, k, 1), strict=True))
    return f"""{clouds.grid_sql(name)},
hh AS (SELECT CAST(greatest(1, (length(bin(greatest(ex, ey, ez))) + {b - 1}) // {b}) AS INTEGER) AS h FROM m),
{alias} AS (SELECT c.*, h, array_to_string(list_transform(generate_series(h - 1, 0, -1), lambda j: chr(CAST(48 + {digit} AS INTEGER))), '') AS path FROM c, hh)"""


def sql_tree(name: str, limit: int = 100, k: int = 2) -> str:
    """CTEs: ``nodes`` of all levels, and ``tree``, the tree's own boxes with their kind."""
    return f"""{sql_points(name, k)},
nodes AS (SELECT level, substr(path, 1, level) AS path, count(*) AS cnt, any_value(h) AS h FROM (SELECT path, h, unnest(generate_series(1, h)) AS level FROM pts) GROUP BY level, substr(path, 1, level)),
tree AS (SELECT n.level, n.path, n.cnt, n.h, CASE WHEN n.level = n.h THEN 'cell' WHEN n.cnt > {limit} THEN 'branch' ELSE 'leaf' END AS kind
  FROM nodes n LEFT JOIN nodes p ON p.level = n.level - 1 AND p.path = substr(n.path, 1, n.level - 1) WHERE n.level = 1 OR p.cnt > {limit})"""


def sql_leaf_points(name: str, limit: int = 100, k: int = 2) -> str:
    """CTE ``lp``: points with the level, path, box side and local coordinates of their leaf."""
    width = k.bit_length() - 1
    local = ", ".join(f"CASE WHEN t.level < p.h THEN {a} % (1::BIGINT << ({width} * (p.h - t.level))) END AS l{a}, {a} - {a} % (1::BIGINT << ({width} * (p.h - t.level))) AS {a}0" for a in "xyz")
    return f"""{sql_tree(name, limit, k)},
lp AS (SELECT p.*, t.level, t.path AS leaf, t.cnt, (1::BIGINT << ({width} * (p.h - t.level))) AS side, {local} FROM (SELECT *, unnest(generate_series(1, h)) AS lv FROM pts) p JOIN tree t ON t.level = p.lv AND t.path = substr(p.path, 1, p.lv) AND t.kind <> 'branch')"""
