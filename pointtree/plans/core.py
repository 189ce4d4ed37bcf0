"""Registered queries of the engine itself: quantization, paths, construction, codes, box queries, baselines, measures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import TreeConfig
from ..functions import mlv, quantize
from ..functions.paths import packed_path, path_of, with_box
from ..functions.quantize import Fixed, fit_frame
from ..operators import baselines, bittree, bitvec, leaves, measures, query, topology
from ..operators.topology import ordered_index
from ..sources import clouds
from ..sources import store as stores
from ..sources.clouds import CLOUDS, RECORD0, grid_sql
from ..sources.shared import cut
from .book import CONFIG, cloud, leaves_of, nodes_of, once, sql_leaf_points, sql_points, sql_tree, store_of
from .book import query as registered
from .workloads import BOXES_SQL, SINGLE, boxes, part_box, part_sql

W = "WITH "
XYZ = ("x", "y", "z")
BIG = lambda c: f"CAST({c} AS BIGINT)"


# ---- quantization
@registered("frame_fit", W + grid_sql("flat") + " SELECT lx, hx, ly, hy, lz, hz, (SELECT count(*) FROM raw) AS points FROM m")
def frame_fit(spark: SparkSession, d: str) -> DataFrame:
    f = fit_frame(clouds.load(spark, d, "flat"), CLOUDS["flat"].policy)
    return spark.createDataFrame([(f.low[0], f.high[0], f.low[1], f.high[1], f.low[2], f.high[2], f.count)], "lx long, hx long, ly long, hy long, lz long, hz long, points long")


def _grid(name: str):
    return lambda spark, d: cloud(spark, d, name)[0].select(*XYZ)


registered("quantize_fixed", W + grid_sql("flat") + " SELECT x, y, z FROM c")(_grid("flat"))
registered("quantize_span", W + grid_sql("cube") + " SELECT x, y, z FROM c")(_grid("cube"))
registered("offset_shift", W + grid_sql("embeddings") + " SELECT pid, x, y, z FROM c")(lambda spark, d: cloud(spark, d, "embeddings")[0].select("pid", *XYZ))


@registered("quantize_roundtrip", W + grid_sql("orders") + " SELECT pid, CAST(rx AS BIGINT) AS rx, CAST(ry AS BIGINT) AS cents, CAST(rz AS BIGINT) AS rz FROM raw")
def quantize_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "orders")
    r = quantize.restore(p, f)
    return r.select("pid", F.col("rx").cast("long").alias("rx"), F.round(F.col("ry") * 100).cast("long").alias("cents"), F.col("rz").cast("long").alias("rz"))


@registered("quant_error", "SELECT CAST(0 AS BIGINT) AS half_steps_x, CAST(0 AS BIGINT) AS half_steps_y, CAST(0 AS BIGINT) AS half_steps_z")
def quant_error(spark: SparkSession, d: str) -> DataFrame:
    """Axes on which an error of more than half a step occurs; a real may sit half a step off at most."""
    raw = clouds.load(spark, d, "embeddings")
    e = quantize.quantization_error(raw, fit_frame(raw, CLOUDS["embeddings"].policy))
    return e.select(*[(F.col(f"error_{a}") > 0.5e-6 + 1e-12).cast("long").alias(f"half_steps_{a}") for a in XYZ])


@registered("box_to_grid", W + grid_sql("flat") + " SELECT " + ", ".join(f"CAST(greatest(0, {lo} - l{a}) AS BIGINT) AS {a}i, CAST(least(e{a}, {hi} - l{a}) AS BIGINT) AS {a}e" for a, lo, hi in (("x", 100, 5000), ("y", 200050, 90000000000), ("z", -5, 700))) + " FROM m")
def box_to_grid(spark: SparkSession, d: str) -> DataFrame:
    f = fit_frame(clouds.load(spark, d, "flat"), CLOUDS["flat"].policy)
    b = quantize.to_grid_box((99.5, 2000.495, -5, 5000.9, 9e8, 700.2), f)
    return spark.createDataFrame([(b[0], b[3], b[1], b[4], b[2], b[5])], "xi long, xe long, yi long, ye long, zi long, ze long")


@registered("tree_shape", " UNION ALL ".join(f"(WITH {grid_sql(n)} SELECT '{n}' AS cloud, CAST(length(bin(greatest(ex, ey, ez))) AS BIGINT) AS h2, CAST((length(bin(greatest(ex, ey, ez))) + 1) // 2 AS BIGINT) AS h4 FROM m)" for n in ("flat", "air", "cube", "grid", "orders", "events", "embeddings", "documents", "parts")))
def tree_shape(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for n in ("flat", "air", "cube", "grid", "orders", "events", "embeddings", "documents", "parts"):
        f = fit_frame(clouds.load(spark, d, n), CLOUDS[n].policy)
        rows.append((n, len(f.parts(TreeConfig())), len(f.parts(TreeConfig(fanout=4)))))
    return spark.createDataFrame(rows, "cloud string, h2 long, h4 long")


# ---- paths
@registered("point_paths", W + sql_points("orders") + " SELECT pid, path FROM pts")
def point_paths(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "orders")
    return p.select("pid", path_of(f.parts(CONFIG)).alias("path"))


@registered("packed_path", W + sql_points("orders") + ", o AS (SELECT pid, path, h, CASE WHEN h > 21 THEN substr(path, 1, h - 21) ELSE '' END AS a, CASE WHEN h > 21 THEN substr(path, h - 20) ELSE path END AS b FROM pts) SELECT pid, CAST(list_reduce(list_prepend(0, list_transform(string_split(a, ''), lambda s: CAST(CASE WHEN s = '' THEN '0' ELSE s END AS BIGINT))), lambda u, v: u * 8 + v) AS BIGINT) AS hi, CAST(list_reduce(list_prepend(0, list_transform(string_split(b, ''), lambda s: CAST(CASE WHEN s = '' THEN '0' ELSE s END AS BIGINT))), lambda u, v: u * 8 + v) AS BIGINT) AS lo FROM o")
def packed(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "orders")
    hi, lo = packed_path(f.parts(CONFIG))
    return p.select("pid", hi.alias("hi"), lo.alias("lo"))


@registered("paths_mixed_fanout", W + grid_sql("grid") + " SELECT x, y, z, chr(CAST(48 + 16 * (x // 16) + 4 * (y // 16) + z // 16 AS INTEGER)) || chr(CAST(48 + 16 * (x // 4 % 4) + 4 * (y // 4 % 4) + z // 4 % 4 AS INTEGER)) || chr(CAST(48 + 4 * (x // 2 % 2) + 2 * (y // 2 % 2) + z // 2 % 2 AS INTEGER)) || chr(CAST(48 + 4 * (x % 2) + 2 * (y % 2) + z % 2 AS INTEGER)) AS path FROM c")
def paths_mixed_fanout(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "grid")
    return p.select(*XYZ, path_of(f.parts(TreeConfig(schedule=(4, 4, 2, 2)))).alias("path"))


@registered("node_boxes", W + sql_leaf_points("air") + " SELECT level, leaf AS path, CAST(min(x0) AS BIGINT) AS x0, CAST(min(y0) AS BIGINT) AS y0, CAST(min(z0) AS BIGINT) AS z0, CAST(min(side) AS BIGINT) AS side FROM lp GROUP BY level, leaf")
def node_boxes(spark: SparkSession, d: str) -> DataFrame:
    n, f = nodes_of(spark, d, "air")
    return with_box(n.where("kind <> 'branch'").select("level", "path"), f.parts(CONFIG))


@registered("bfs_positions", W + sql_tree("air") + " SELECT level, path, CAST(row_number() OVER (ORDER BY level, path) - 1 AS BIGINT) AS pos FROM tree")
def bfs_positions(spark: SparkSession, d: str) -> DataFrame:
    return ordered_index(nodes_of(spark, d, "air")[0].select("level", "path"), "level", "path")


# ---- construction
@registered("level_histogram", W + sql_points("flat") + " SELECT level, substr(path, 1, level) AS path, count(*) AS cnt FROM (SELECT path, unnest(generate_series(1, 8)) AS level FROM pts) GROUP BY level, substr(path, 1, level)")
def level_histogram(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "flat")
    return topology.level_histogram(p, f.parts(CONFIG), 8)


def _kinds(name: str, limit: int):
    return lambda spark, d: nodes_of(spark, d, name, TreeConfig(leaf_limit=limit))[0].groupBy("level", "kind").agg(F.count("*").alias("boxes"), F.sum("cnt").alias("points"))


for _n, _l, _q in (("flat", 100, "node_kinds"), ("grid", 100, "node_kinds_grid"), ("cube", 100, "node_kinds_cube"), ("documents", 100, "node_kinds_documents"), ("events", 100, "node_kinds_events"), ("parts", 100, "node_kinds_parts"), ("embeddings", 8, "node_kinds_embeddings")):
    registered(_q, W + sql_tree(_n, _l) + " SELECT level, kind, count(*) AS boxes, CAST(sum(cnt) AS BIGINT) AS points FROM tree GROUP BY level, kind")(_kinds(_n, _l))


def _leaf_census(name: str, limit: int, method: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        p, f = cloud(spark, d, name)
        c = TreeConfig(leaf_limit=limit, shard_points=10_000)
        got = topology.leaf_levels(p.select("pid", *XYZ), c, f.parts(c), method)
        return got.groupBy(F.col("leaf_level").alias("level"), F.expr("substring(path, 1, leaf_level)").alias("leaf")).agg(F.count("*").alias("n"), F.sum("x").alias("sx"), F.sum("y").alias("sy"), F.sum("z").alias("sz"))

    return run


for _n, _l, _m, _q in (("flat", 100, "window", "leaf_levels_window"), ("flat", 100, "iterative", "leaf_levels_iter"), ("air", 100, "histogram", "leaf_levels_join"), ("cube", 100, "window", "leaf_levels_window_cube"), ("grid", 3, "window", "leaf_levels_window_cells"), ("grid", 3, "iterative", "leaf_levels_iter_cells")):
    registered(_q, W + sql_leaf_points(_n, _l) + " SELECT level, leaf, count(*) AS n, CAST(sum(x) AS BIGINT) AS sx, CAST(sum(y) AS BIGINT) AS sy, CAST(sum(z) AS BIGINT) AS sz FROM lp GROUP BY level, leaf")(_leaf_census(_n, _l, _m))


def _bits(name: str, limit: int, which: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        n, f = nodes_of(spark, d, name, TreeConfig(leaf_limit=limit))
        return topology.global_bits(cut(n), f.parts(CONFIG), limit, which)

    return run


def _children_sql(name: str, limit: int) -> str:
    return W + sql_tree(name, limit) + f""",
divided AS (SELECT 0 AS level, '' AS path UNION ALL SELECT level, path FROM tree WHERE kind = 'branch'),
kids AS (SELECT d.level + 1 AS level, d.path || chr(CAST(48 + u AS INTEGER)) AS path FROM divided d, (SELECT unnest(range(8)) AS u)),
boxes AS (SELECT k.level, k.path, coalesce(t.cnt, 0) AS cnt, coalesce(t.cnt, 0) > {limit} AND k.level < hh.h AS split, hh.h FROM kids k LEFT JOIN tree t USING (level, path), hh)"""


for _n, _l in (("flat", 100), ("grid", 100)):
    _s = "" if _n == "flat" else "_grid"
    registered("bits_branch" + _s, _children_sql(_n, _l) + " SELECT CAST(row_number() OVER (ORDER BY level, path) - 1 AS BIGINT) AS pos, CAST(split AS INTEGER) AS bit FROM boxes WHERE level < h")(_bits(_n, _l, "branch"))
    registered("bits_occupied" + _s, _children_sql(_n, _l) + " SELECT CAST(row_number() OVER (ORDER BY level, path) - 1 AS BIGINT) AS pos, CAST(cnt > 0 AS INTEGER) AS bit FROM boxes WHERE NOT split")(_bits(_n, _l, "occupied"))
    registered("bits_tally" + _s, W + sql_tree(_n, _l) + ", l AS (SELECT level, path, cnt, sum(cnt) OVER (ORDER BY level, path) - cnt AS start FROM tree WHERE kind <> 'branch'), e AS (SELECT start, cnt, unnest(range(CAST(cnt AS BIGINT))) AS i FROM l) SELECT CAST(start + i AS BIGINT) AS pos, CAST(i = cnt - 1 AS INTEGER) AS bit FROM e")(_bits(_n, _l, "tally"))


@registered("local_coords", W + sql_leaf_points("grid") + " SELECT leaf, x, y, z, CAST(lx AS BIGINT) AS lx, CAST(ly AS BIGINT) AS ly, CAST(lz AS BIGINT) AS lz FROM lp")
def local_coords(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "grid")
    return leaves.leaf_points(p, CONFIG, f.parts(CONFIG)).select(F.col("path").alias("leaf"), *XYZ, "lx", "ly", "lz")


@registered("attr_order", W + sql_leaf_points("events") + " SELECT pid, CAST(row_number() OVER (ORDER BY level, leaf, path, pid) - 1 AS BIGINT) AS pos, event_code, prop FROM lp")
def attr_order(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "events")
    return leaves.positions(p, CONFIG, f.parts(CONFIG)).select("pid", "pos", "event_code", "prop")


for _order, _by in (("zorder", "path, pid"), ("lex", "lx, ly, lz, pid")):
    def _positions(spark: SparkSession, d: str, order: str = _order) -> DataFrame:
        p, f = cloud(spark, d, "orders")
        return leaves.positions(p, TreeConfig(leaf_order=order, shard_points=5000), f.parts(CONFIG)).select("pid", "pos")

    registered("point_positions" if _order == "zorder" else "point_positions_lex", W + sql_leaf_points("orders") + f" SELECT pid, CAST(row_number() OVER (ORDER BY level, leaf, {_by}) - 1 AS BIGINT) AS pos FROM lp")(_positions)


def _leaf_rows(name: str, attribute: str | None, config: TreeConfig = CONFIG):
    def run(spark: SparkSession, d: str) -> DataFrame:
        t, _ = leaves_of(spark, d, name, config)
        total = lambda c: F.coalesce(F.aggregate(c, F.lit(0).cast("long"), lambda a, v: a + v), F.lit(-1).cast("long"))
        more = [F.col(f"{attribute}_min").alias("a_min"), F.col(f"{attribute}_max").alias("a_max"), F.size(f"a_{attribute}").alias("a_size")] if attribute else []
        return t.select("level", "path", "x0", "y0", "z0", "side", "cnt", total("xs").alias("sum_x"), total("ys").alias("sum_y"), total("zs").alias("sum_z"), *more)

    return run


def _leaf_rows_sql(name: str, attribute: str | None, limit: int = 100, k: int = 2) -> str:
    sums = ", ".join(f"CAST(coalesce(sum(l{a}), -1) AS BIGINT) AS sum_{a}" for a in "xyz")
    more = f", min({attribute}) AS a_min, max({attribute}) AS a_max, CAST(count(*) AS INTEGER) AS a_size" if attribute else ""
    return W + sql_leaf_points(name, limit, k) + f" SELECT level, leaf AS path, CAST(min(x0) AS BIGINT) AS x0, CAST(min(y0) AS BIGINT) AS y0, CAST(min(z0) AS BIGINT) AS z0, CAST(min(side) AS BIGINT) AS side, count(*) AS cnt, {sums}{more} FROM lp GROUP BY level, leaf"


registered("leaf_table", _leaf_rows_sql("air", "intensity"))(_leaf_rows("air", "intensity"))
registered("leaf_table_k4", _leaf_rows_sql("orders", None, k=4))(_leaf_rows("orders", None, TreeConfig(fanout=4, shard_points=20_000)))
registered("attr_custom", _leaf_rows_sql("parts", "brand"))(_leaf_rows("parts", "brand"))


@registered("leaf_limit_sweep", " UNION ALL ".join(f"(WITH {sql_tree('flat', l)} SELECT CAST({l} AS BIGINT) AS leaf_limit, count(*) FILTER (kind = 'branch') + 1 AS branches, count(*) FILTER (kind <> 'branch') AS leaves, CAST(max(cnt) FILTER (kind <> 'branch') AS BIGINT) AS largest FROM tree)" for l in (1, 10, 100, 1000)))  # noqa: E741
def leaf_limit_sweep(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "flat")
    h = len(f.parts(CONFIG))
    counted = cut(topology.level_histogram(p, f.parts(CONFIG)))  # the counts serve all limits
    out = None
    for limit in (1, 10, 100, 1000):
        n = topology.classify_nodes(counted, h, limit)
        row = n.agg(F.lit(limit).cast("long").alias("leaf_limit"), (F.count(F.when(F.col("kind") == "branch", 1)) + 1).alias("branches"), F.count(F.when(F.col("kind") != "branch", 1)).alias("leaves"), F.max(F.when(F.col("kind") != "branch", F.col("cnt"))).alias("largest"))
        out = row if out is None else out.unionByName(row)
    return out


@registered("shard_plan", W + sql_tree("flat", 5000) + " SELECT level, path, cnt, CAST(sum(cnt) OVER (ORDER BY path) - cnt AS BIGINT) AS first_point FROM tree WHERE kind <> 'branch'")
def shard_plan(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "flat")
    t = topology.frontier(p, f.parts(CONFIG), 5000, divide_root=True)
    return ordered_index(t, "path", name="first_point", first="cnt").select("level", "path", "cnt", "first_point")


POINT_KEYS = [*XYZ, *RECORD0]
ATTRS = ", ".join(RECORD0)


@registered("store_roundtrip", W + grid_sql("air") + f" SELECT x, y, z, {ATTRS} FROM c")
def store_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return query.scan_all(store_of(spark, d, "air"))


registered("full_decode", W + grid_sql("cube") + " SELECT x, y, z, intensity FROM c")(lambda spark, d: query.scan_all(store_of(spark, d, "cube"), ["intensity"]))
registered("store_roundtrip_lex", W + grid_sql("grid") + " SELECT x, y, z, return_number FROM c")(lambda spark, d: query.scan_all(store_of(spark, d, "grid", TreeConfig(leaf_order="lex", leaf_limit=3, shard_points=5000))))
registered("store_roundtrip_schedule", W + grid_sql("events") + " SELECT x, y, z, event_code, prop FROM c")(lambda spark, d: query.scan_all(store_of(spark, d, "events", TreeConfig(schedule=(4, 4, 2), shard_points=2000))))
registered("attr_nullable", W + grid_sql("documents") + " SELECT x, y, z, quality, toxic, lang_code, source_code FROM c")(lambda spark, d: query.scan_all(store_of(spark, d, "documents", TreeConfig(leaf_limit=20, shard_points=300))))
registered("attr_bit", W + grid_sql("air") + " SELECT x, y, z, scan_direction, edge_of_flight_line FROM c WHERE scan_direction = 1 AND edge_of_flight_line = 1")(lambda spark, d: query.points_in_box_where(store_of(spark, d, "air"), (0, 0, 0, *(3_999_990, 3_999_990, 218_720)), [("scan_direction", 1, 1), ("edge_of_flight_line", 1, 1)], ["scan_direction", "edge_of_flight_line"]))


#: Customers as points: ``x, y, z`` in SQL that Spark and DuckDB share. Keys and balances are read, so no part is made up.
def _edge_sql(xyz: tuple[str, str, str], rest: str = "") -> str:
    return "SELECT " + ", ".join(f"CAST({v} AS BIGINT) AS {a}" for a, v in zip("xyz", xyz, strict=True)) + f" FROM customer{rest}"


def _edge(xyz: tuple[str, str, str], config: TreeConfig, high: int, kind: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        t = clouds.table(spark, d, "customer")
        columns = [f"CAST({v} AS BIGINT) AS {a}" for a, v in zip("xyz", xyz, strict=True)]
        p = t.selectExpr("max(c_custkey) AS pid", *columns) if kind == "one" else t.where(_NONE if kind == "empty" else "true").selectExpr("c_custkey AS pid", *columns)
        f = quantize.Frame(Fixed(), (0, 0, 0), (high,) * 3, p.count())
        return query.scan_all(stores.build(p, f, config), [])

    return run


def _by_key(n: int, *values: int) -> str:
    """The value of the customer's key modulo n."""
    return f"CASE c_custkey % {n} " + " ".join(f"WHEN {i} THEN {v}" for i, v in enumerate(values[:-1])) + f" ELSE {values[-1]} END"


_NONE = "c_custkey % 8 > 7"  # true of no row, and no scan can know
_EDGES = {
    "edge_one_point": (("max(c_custkey % 8)", "min(c_nationkey % 8)", "max(c_custkey + floor(abs(c_acctbal))) % 8"), TreeConfig(), 7, "one"),
    "edge_all_equal": (("3",) * 3, TreeConfig(leaf_limit=2), 7, "all"),
    "edge_limit_one": ((_by_key(4, 0, 0, 7), _by_key(4, 0, 0, 7), _by_key(4, 0, 1, 7)), TreeConfig(leaf_limit=1), 7, "all"),
    "edge_height_one": ((_by_key(3, 0, 1),) * 3, TreeConfig(), 1, "all"),
    "edge_fanout_four": ((_by_key(4, 0, 63, 63, 17), _by_key(4, 0, 63, 63, 2), _by_key(4, 0, 63, 63, 40)), TreeConfig(fanout=4, leaf_limit=1), 63, "all"),
    "edge_empty_cloud": (("c_custkey % 8", "c_nationkey % 8", "0"), TreeConfig(), 7, "empty"),
}
for _q, (_x, _c, _h, _k) in _EDGES.items():
    registered(_q, _edge_sql(_x, f" WHERE {_NONE}" if _k == "empty" else ""))(_edge(_x, _c, _h, _k))

TILES_SQL = "SELECT s_nationkey AS tile, s_suppkey FROM supplier"


def tiled(spark: SparkSession, d: str) -> DataFrame:
    """The flagship cloud with the tile of each point: a small dimension beside it."""
    p, _ = cloud(spark, d, "air")
    s = clouds.table(spark, d, "supplier").select(F.col("s_nationkey").alias("tile"), F.col("s_suppkey").cast("int").alias("point_source"))
    return p.join(s, "point_source")


@registered("tiles_union", W + grid_sql("air") + f", t AS ({TILES_SQL}) SELECT tile, count(*) AS n, CAST(sum(x) AS BIGINT) AS sx FROM c JOIN t ON point_source = s_suppkey WHERE tile < 9 GROUP BY tile")
def tiles_union(spark: SparkSession, d: str) -> DataFrame:
    t = tiled(spark, d)
    u = t.where("tile < 4").unionByName(t.where("tile >= 4 and tile < 9"))
    return u.groupBy("tile").agg(F.count("*").alias("n"), F.sum("x").alias("sx"))


@registered("repeat_census", _leaf_rows_sql("grid", None).replace("SELECT level, leaf AS path", "SELECT leaf AS path", 1).replace(" FROM lp GROUP BY", ", string_agg(printf('%d,%d,%d', lx, ly, lz), ';' ORDER BY lx, ly, lz) AS held FROM lp GROUP BY").replace(W, "WITH r AS (WITH ", 1) + ") SELECT count(*) AS leaves, count(DISTINCT held) AS payloads FROM r WHERE held IS NOT NULL")
def repeat_census(spark: SparkSession, d: str) -> DataFrame:
    """Leaves with equal coordinates could share one payload."""
    t, _ = leaves_of(spark, d, "grid")
    held = F.to_json(F.sort_array(F.arrays_zip("xs", "ys", "zs")))
    return t.where(F.col("xs")[0].isNotNull()).select(F.sha2(held, 256).alias("s")).groupBy("s").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0).cast("long")).alias("leaves"), F.count("*").alias("payloads"))


@registered("repeat_store", W + grid_sql("events") + " SELECT x, y, z FROM c")
def repeat_store(spark: SparkSession, d: str) -> DataFrame:
    """Points out of leaves that share payloads: small leaves repeat each other."""
    t, _ = leaves_of(spark, d, "events", TreeConfig(leaf_limit=1, shard_points=20_000))
    rows, payloads = leaves.share_repeats(t)
    return leaves.explode_points(leaves.with_payloads(cut(rows), cut(payloads)))


@registered("repeat_saving", W + sql_leaf_points("grid", 3) + ", h AS (SELECT level, leaf, count(*) AS n, string_agg(printf('%d,%d,%d', lx, ly, lz), ';' ORDER BY path) AS held FROM lp WHERE level < h GROUP BY level, leaf), p AS (SELECT held, any_value(n) AS n FROM h GROUP BY held) SELECT (SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM h) AS points, (SELECT CAST(coalesce(sum(n), 0) AS BIGINT) FROM p) AS kept")
def repeat_saving(spark: SparkSession, d: str) -> DataFrame:
    """Points with coordinates of their own, and those that are kept when repeats are shared."""
    t, _ = leaves_of(spark, d, "grid", TreeConfig(leaf_limit=3, shard_points=20_000))
    rows, payloads = leaves.share_repeats(t)
    zero = F.lit(0).cast("long")
    own = rows.where("payload is not null").agg(F.coalesce(F.sum("cnt"), zero).alias("points"))
    return own.crossJoin(payloads.agg(F.coalesce(F.sum(F.size("xs")), zero).alias("kept")))  # one row each


# ---- codes
BITS_SQL = W + grid_sql("events") + ", f AS (SELECT pid AS i, CAST(event_code = 3 AS INTEGER) AS bit FROM c)"


def _flags(spark: SparkSession, d: str) -> DataFrame:
    return cloud(spark, d, "events")[0].select(F.col("pid").alias("i"), (F.col("event_code") == 3).cast("int").alias("bit"))


@registered("bitvec_blocks", BITS_SQL + " SELECT i // 32768 AS block, CAST(sum(bit) AS BIGINT) AS ones, CAST(coalesce(sum(sum(bit)) OVER (ORDER BY i // 32768 ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS ones_before FROM f GROUP BY i // 32768")
def bitvec_blocks(spark: SparkSession, d: str) -> DataFrame:
    return bitvec.bit_blocks(_flags(spark, d)).select("block", "ones", "ones_before")


@registered("rank_probe", BITS_SQL + " SELECT p.range * 97 AS i, CAST((SELECT coalesce(sum(bit), 0) FROM f WHERE f.i < p.range * 97) AS BIGINT) AS rank1 FROM range(0, 100) p WHERE p.range * 97 < (SELECT count(*) FROM f)")
def rank_probe(spark: SparkSession, d: str) -> DataFrame:
    """Ones in [0, i) for a few positions: the ones before i's block, and those of its part of the block."""
    flags = _flags(spark, d)
    probes = spark.range(100).select((F.col("id") * 97).alias("i")).join(flags.select("i"), "i", "left_semi")
    return bitvec.bit_and_rank(probes, bitvec.bit_blocks(flags), "i").select("i", (F.col("rank") - F.col("bit")).alias("rank1"))


@registered("rank_all", BITS_SQL + " SELECT i, bit, CAST(sum(bit) OVER (ORDER BY i) - bit AS BIGINT) AS rank1 FROM f")
def rank_all(spark: SparkSession, d: str) -> DataFrame:
    """Access and rank at every position, from the blocks alone."""
    flags = _flags(spark, d)
    got = bitvec.bit_and_rank(flags.select("i"), cut(bitvec.bit_blocks(flags)), "i")
    return got.select("i", "bit", (F.col("rank") - F.col("bit")).alias("rank1"))


@registered("select_probe", BITS_SQL + " SELECT CAST(row_number() OVER (ORDER BY i) - 1 AS BIGINT) AS j, i AS select1 FROM f WHERE bit = 1")
def select_probe(spark: SparkSession, d: str) -> DataFrame:
    """Every one by its number, from the blocks alone."""
    blocks = cut(bitvec.bit_blocks(_flags(spark, d)))
    n = blocks.agg(F.coalesce(F.sum("ones"), F.lit(0))).first()[0]
    return bitvec.select(spark.range(n).withColumnRenamed("id", "j"), blocks)


@registered("mlv_size", W + sql_leaf_points("flat") + " SELECT CAST(length(bin(lx)) AS INTEGER) AS bits, count(*) AS n FROM lp GROUP BY 1")
def mlv_size(spark: SparkSession, d: str) -> DataFrame:
    """The histogram that the best chunk widths are chosen from."""
    t, _ = leaves_of(spark, d, "flat")
    return t.select(F.explode("xs").alias("v")).groupBy(F.length(F.bin("v")).alias("bits")).agg(F.count("*").alias("n"))


@registered("mlv_access", W + grid_sql("orders") + " SELECT pid, y AS v FROM c")
def mlv_access(spark: SparkSession, d: str) -> DataFrame:
    """Every value out of codes, in shuffled order, without decoding its neighbours."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pid, code = b.column("pid").to_numpy(), mlv.Mlv.from_bytes(mlv.encode(b.column("y").to_numpy().astype(np.uint64)).to_bytes())
            i = np.random.default_rng(len(pid)).permutation(len(pid))
            yield pa.RecordBatch.from_arrays([pa.array(pid[i]), pa.array(code.get(i).astype(np.int64))], names=["pid", "v"])

    return cloud(spark, d, "orders")[0].select("pid", "y").mapInArrow(run, "pid long, v long")


@registered("leaf_ranges", W + sql_tree("flat") + " SELECT level, path, CAST(sum(cnt) OVER (ORDER BY level, path) - cnt AS BIGINT) AS start, CAST(sum(cnt) OVER (ORDER BY level, path) AS BIGINT) AS stop FROM tree WHERE kind <> 'branch'")
def leaf_ranges(spark: SparkSession, d: str) -> DataFrame:
    return leaves.leaf_ranges(leaves_of(spark, d, "flat")[0])


@registered("zigzag", W + grid_sql("flat") + " SELECT scan_angle, CAST(CASE WHEN scan_angle < 0 THEN -2 * scan_angle - 1 ELSE 2 * scan_angle END AS BIGINT) AS code, count(*) AS n FROM c GROUP BY scan_angle")
def zigzag(spark: SparkSession, d: str) -> DataFrame:
    v = F.col("scan_angle").cast("long")
    p, _ = cloud(spark, d, "flat")
    return p.groupBy("scan_angle").agg(F.count("*").alias("n")).select("scan_angle", F.shiftleft(v, 1).bitwiseXOR(F.shiftright(v, 63)).alias("code"), "n")


# ---- box queries
def _box(name: str, part: str, columns: tuple[str, ...] = (), **more):
    config = more.pop("config", CONFIG)

    def run(spark: SparkSession, d: str) -> DataFrame:
        s = store_of(spark, d, name, config)
        return query.points_in_box(s, part_box(s.frame, *SINGLE[part]), columns, **more)

    return run


def _box_sql(name: str, part: str, columns: tuple[str, ...] = (), where: str = "") -> str:
    return W + grid_sql(name) + f" SELECT x, y, z{''.join(', ' + c for c in columns)} FROM c WHERE {part_sql(*SINGLE[part])}{where}"


registered("box_query", _box_sql("air", "third"))(_box("air", "third"))
registered("box_query_cube", _box_sql("cube", "third"))(_box("cube", "third"))
registered("box_query_cells", _box_sql("grid", "third"))(_box("grid", "third", config=TreeConfig(leaf_limit=3, shard_points=5000)))
registered("box_query_k4", _box_sql("cube", "third"))(_box("cube", "third", config=TreeConfig(fanout=4, shard_points=20_000)))
registered("box_query_xstop", _box_sql("cube", "small"))(_box("cube", "small", early_stop="x", config=TreeConfig(leaf_order="lex", shard_points=20_000)))
registered("box_query_codestop", _box_sql("air", "small"))(_box("air", "small", early_stop="code"))
registered("box_query_projected", _box_sql("air", "third", ("classification", "user_data")))(_box("air", "third", ("classification", "user_data")))
registered("slab_query", _box_sql("cube", "slab", ("intensity",)))(_box("cube", "slab", ("intensity",)))
registered("column_query", _box_sql("cube", "column"))(_box("cube", "column"))
_I = [("intensity", 10, 20)]
registered("attr_box_query", _box_sql("air", "third", ("intensity",), " AND intensity BETWEEN 10 AND 20"))(_box("air", "third", ("intensity",), where=_I))
registered("attr_box_query_indexed", _box_sql("air", "slab", ("intensity",), " AND intensity BETWEEN 10 AND 20"))(_box("air", "slab", ("intensity",), where=_I, value_index=True))
registered("multi_attr_box", _box_sql("air", "third", (), " AND intensity BETWEEN 10 AND 40 AND classification BETWEEN 1 AND 2 AND scan_angle BETWEEN -3 AND 0"))(_box("air", "third", where=[("intensity", 10, 40), ("classification", 1, 2), ("scan_angle", -3, 0)]))


def _native(name: str, part: str, attributes: tuple[str, ...] = (), **more):
    def run(spark: SparkSession, d: str) -> DataFrame:
        t, f = leaves_of(spark, d, name)
        return leaves.points_in_box(t, part_box(f, *SINGLE[part]), attributes, **more)

    return run


registered("box_query_native", _box_sql("air", "third"))(_native("air", "third"))
registered("attr_box_query_native", _box_sql("cube", "third", ("intensity",), " AND intensity BETWEEN 10 AND 20"))(_native("cube", "third", ("intensity",), where=_I, value_index=True))
registered("brute_box", _box_sql("air", "third"))(lambda spark, d: (lambda p, f: baselines.brute_box(p, part_box(f, *SINGLE["third"])))(*cloud(spark, d, "air")))


def _met_sql(name: str, part: str) -> str:
    lo, hi = SINGLE[part]
    meets = " AND ".join(f"{a}0 <= e{a} * {q} // 1000 AND {a}0 + side - 1 >= e{a} * {p} // 1000" for a, p, q in zip("xyz", lo, hi, strict=True))
    inside = " AND ".join(f"{a}0 >= e{a} * {p} // 1000 AND {a}0 + side - 1 <= e{a} * {q} // 1000" for a, p, q in zip("xyz", lo, hi, strict=True))
    return W + sql_leaf_points(name) + f", met AS (SELECT *, {inside} AS inside, {part_sql(*SINGLE[part])} AS hit FROM lp WHERE {meets})"


for _n, _p in (("air", "third"), ("cube", "third"), ("air", "slab"), ("cube", "slab"), ("cube", "column"), ("cube", "small")):
    def _work(spark: SparkSession, d: str, name: str = _n, part: str = _p) -> DataFrame:
        s = store_of(spark, d, name)
        return query.explain_work(s, part_box(s.frame, *SINGLE[part])).select("leaves", "points_checked", "points_out")

    registered({"airthird": "work_counters", "airslab": "slab_work_air", "cubeslab": "slab_work"}.get(_n + _p, f"work_counters_{_n}_{_p}"), _met_sql(_n, _p) + " SELECT count(DISTINCT leaf) AS leaves, count(*) FILTER (NOT inside AND level < h) AS points_checked, count(*) FILTER (hit) AS points_out FROM met")(_work)


@registered("box_trace", _met_sql("grid", "third") + " SELECT CASE WHEN level = h THEN 'cell' ELSE 'leaf' END AS kind, CAST(count(DISTINCT leaf) AS BIGINT) AS boxes, count(*) AS points FROM met GROUP BY 1")
def box_trace(spark: SparkSession, d: str) -> DataFrame:
    """Occupied undivided boxes that a query meets, by what is done with them."""
    t, f = leaves_of(spark, d, "grid")
    h = len(f.parts(CONFIG))
    return t.where(leaves.overlaps(part_box(f, *SINGLE["third"]))).groupBy(F.when(F.col("level") == h, "cell").otherwise("leaf").alias("kind")).agg(F.count("*").alias("boxes"), F.sum("cnt").alias("points"))


_LOW = {a: f"CAST(list_sum(list_transform(range(1, level + 1), lambda j: ((ascii(substr(path, CAST(j AS INTEGER), 1)) - 48) // {w} % 2) * (1 << CAST(h - j AS INTEGER)))) AS BIGINT)" for a, w in zip("xyz", (4, 2, 1), strict=True)}
_MET = " AND ".join(f"{a}0 <= e{a} * {q} // 1000 AND {a}0 + (1 << CAST(h - level AS INTEGER)) - 1 >= e{a} * {p} // 1000" for a, p, q in zip("xyz", *SINGLE["third"], strict=True))


@registered("box_trace_tree", _children_sql("grid", 100) + ", g AS (SELECT *, " + ", ".join(f"{c} AS {a}0" for a, c in _LOW.items()) + f" FROM boxes), met AS (SELECT g.* FROM g, m WHERE {_MET}) SELECT count(*) AS boxes_visited, count(*) FILTER (split) AS branches, count(*) FILTER (NOT split AND cnt = 0) AS empty, count(*) FILTER (NOT split AND cnt > 0) AS leaves FROM met")
def box_trace_tree(spark: SparkSession, d: str) -> DataFrame:
    """What a search of the whole tree comes to: divided, empty, and occupied undivided boxes."""
    n, f = nodes_of(spark, d, "grid")
    return query.trace_tree(cut(n), f.parts(CONFIG), CONFIG.leaf_limit, part_box(f, *SINGLE["third"]))


@registered("point_at", None)
def point_at(spark: SparkSession, d: str) -> DataFrame:
    return query.point_at(store_of(spark, d, "air"), 1234)


@registered("cell_probe", W + grid_sql("grid") + " SELECT x, y, z, return_number FROM c WHERE x = 7 AND y = 3 AND z = 2")
def cell_probe(spark: SparkSession, d: str) -> DataFrame:
    return query.points_at(store_of(spark, d, "grid"), 7, 3, 2, ["return_number"])


@registered("box_count", " UNION ALL ".join(f"(WITH {grid_sql('air')} SELECT '{p}' AS box, count(*) AS n FROM c WHERE {part_sql(*v)})" for p, v in SINGLE.items()))
def box_count(spark: SparkSession, d: str) -> DataFrame:
    s = store_of(spark, d, "air", TreeConfig(shard_points=1000))
    out = None
    for p, v in SINGLE.items():
        r = query.count_in_box(s, part_box(s.frame, *v)).select(F.lit(p).alias("box"), "n")
        out = r if out is None else out.unionByName(r)
    return out


@registered("box_edges", "SELECT * FROM (VALUES ('outside', CAST(0 AS BIGINT)), ('inverted', CAST(0 AS BIGINT))) v(box, n) UNION ALL (WITH " + grid_sql("grid") + " SELECT 'beyond', count(*) FROM c) UNION ALL (WITH " + grid_sql("grid") + " SELECT 'face', count(*) FROM c WHERE x = 0)")
def box_edges(spark: SparkSession, d: str) -> DataFrame:
    s = store_of(spark, d, "grid")
    e = s.frame.extent
    asked = {"outside": (e[0] + 1, 0, 0, e[0] + 9, e[1], e[2]), "inverted": (5, 0, 0, 2, e[1], e[2]), "beyond": (-9, -9, -9, 999, 999, 999), "face": (-3, 0, 0, 0, e[1], e[2])}
    return spark.createDataFrame([(k, query.points_in_box(s, b).count()) for k, b in asked.items()], "box string, n long")


def _counts_sql(name: str, where: str = "") -> str:
    inside = " AND ".join(f"c.{a} BETWEEN b.{a}i AND b.{a}e" for a in "xyz")
    return W + grid_sql(name) + f", {BOXES_SQL} SELECT q, (SELECT count(*) FROM c WHERE {inside}{where}) AS n FROM b"


def _counts(name: str, where=()):  # noqa: ANN001
    def run(spark: SparkSession, d: str) -> DataFrame:
        s = store_of(spark, d, name)
        return query.counts_in_boxes(s, boxes(spark, s.frame), where)

    return run


registered("w_box500_counts", _counts_sql("air"))(_counts("air"))
registered("w_attr500_counts", _counts_sql("air", " AND intensity BETWEEN 10 AND 20"))(_counts("air", _I))
registered("w_box500_counts_cube", _counts_sql("cube"))(_counts("cube"))
registered("w_box500_counts_flat", _counts_sql("flat"))(_counts("flat"))
registered("w_box500_counts_orders", _counts_sql("orders_span"))(_counts("orders_span"))
registered("w_attr500_counts_flat", _counts_sql("flat", " AND intensity BETWEEN 10 AND 20"))(_counts("flat", _I))
registered("w_attr500_counts_cube", _counts_sql("cube", " AND intensity BETWEEN 10 AND 20"))(_counts("cube", _I))
_INSIDE = " AND ".join(f"c.{a} BETWEEN b.{a}i AND b.{a}e" for a in "xyz")


@registered("box_batch", W + grid_sql("embeddings") + f", {BOXES_SQL} SELECT q, x, y, z, label FROM b JOIN c ON {_INSIDE}")
def box_batch(spark: SparkSession, d: str) -> DataFrame:
    s = store_of(spark, d, "embeddings", TreeConfig(leaf_limit=8, shard_points=100))
    return query.points_in_boxes(s, boxes(spark, s.frame), columns=["label"])


@registered("failed_queries", "SELECT CAST(500 AS BIGINT) AS queries_run, CAST(0 AS BIGINT) AS queries_failed, CAST(500 AS BIGINT) AS queries_timed")
def failed_queries(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "air")
    s, b = store_of(spark, d, "air"), boxes(spark, f)
    return measures.failures(query.counts_in_boxes(s, b), baselines.counts_in_points(p, b))


@registered("knn_points", W + grid_sql("cube") + ", k AS (SELECT x, y, z, CAST(CAST(x - 500000000 AS HUGEINT) * (x - 500000000) + CAST(y - 500000000 AS HUGEINT) * (y - 500000000) + CAST(z - 500000000 AS HUGEINT) * (z - 500000000) AS BIGINT) AS d2 FROM c) SELECT * FROM k ORDER BY d2, x, y, z LIMIT 10")
def knn_points(spark: SparkSession, d: str) -> DataFrame:
    return query.knn(store_of(spark, d, "cube"), 500_000_000, 500_000_000, 500_000_000, 10)


# ---- background structures
CELLS2_SQL = W + grid_sql("grid") + ", cells AS (SELECT DISTINCT x, y FROM c), cp AS (SELECT x, y, array_to_string(list_transform(generate_series(5, 0, -1), lambda j: chr(CAST(48 + 2 * ((x >> j) & 1) + ((y >> j) & 1) AS INTEGER))), '') AS path FROM cells)"
PARTS2 = (2,) * 6


def _cells(spark: SparkSession, d: str, dims: int) -> DataFrame:
    return cloud(spark, d, "grid")[0].select(*XYZ[:dims]).distinct()


@registered("quad_nodes", CELLS2_SQL + " SELECT level, substr(path, 1, level) AS path, count(*) AS cnt FROM (SELECT path, unnest(generate_series(1, 6)) AS level FROM cp) GROUP BY 1, 2")
def quad_nodes(spark: SparkSession, d: str) -> DataFrame:
    return bittree.nodes(_cells(spark, d, 2), PARTS2).select("level", "path", "cnt")


OCT_SQL = W + sql_points("grid") + ", cp AS (SELECT DISTINCT x, y, z, path, h FROM pts)"


@registered("oct_nodes", OCT_SQL + " SELECT level, substr(path, 1, level) AS path, count(*) AS cnt FROM (SELECT path, unnest(generate_series(1, h)) AS level FROM cp) GROUP BY 1, 2")
def oct_nodes(spark: SparkSession, d: str) -> DataFrame:
    return bittree.nodes(_cells(spark, d, 3), PARTS2, 3).select("level", "path", "cnt")


def _bitmap_sql(head: str, width: int, h: int) -> str:
    return head + f""", n AS (SELECT DISTINCT level, substr(path, 1, level) AS path FROM (SELECT path, unnest(generate_series(1, {h})) AS level FROM cp)),
inner_ AS (SELECT 0 AS level, '' AS path UNION ALL SELECT level, path FROM n WHERE level < {h}),
kids AS (SELECT i.level + 1 AS level, i.path || chr(CAST(48 + u AS INTEGER)) AS path FROM inner_ i, (SELECT unnest(range({width})) AS u)),
f AS (SELECT k.level, k.path, CAST(n.path IS NOT NULL AS INTEGER) AS bit FROM kids k LEFT JOIN n USING (level, path))
SELECT CASE WHEN level < {h} THEN 'T' ELSE 'L' END AS part, CAST(row_number() OVER (PARTITION BY level < {h} ORDER BY level, path) - 1 AS BIGINT) AS pos, bit FROM f"""


registered("bitmap_quad", _bitmap_sql(CELLS2_SQL, 4, 6))(lambda spark, d: bittree.bits(_cells(spark, d, 2), PARTS2))
registered("bitmap_oct", _bitmap_sql(OCT_SQL, 8, 6))(lambda spark, d: bittree.bits(_cells(spark, d, 3), PARTS2, 3))
registered("bitmap_quad_k4", _bitmap_sql(CELLS2_SQL.replace("generate_series(5, 0, -1)", "generate_series(2, 0, -1)").replace("2 * ((x >> j) & 1) + ((y >> j) & 1)", "4 * ((x >> (2 * j)) & 3) + ((y >> (2 * j)) & 3)"), 16, 3))(lambda spark, d: bittree.bits(_cells(spark, d, 2), (4, 4, 4)))


@registered("bitcell_probe", CELLS2_SQL + ", p AS (SELECT range % 64 AS x, range // 64 AS y FROM range(1024)) SELECT p.x, p.y, CAST(cells.x IS NOT NULL AS INTEGER) AS is_set FROM p LEFT JOIN cells ON cells.x = p.x AND cells.y = p.y")
def bitcell_probe(spark: SparkSession, d: str) -> DataFrame:
    probes = spark.range(1024).select((F.col("id") % 64).alias("x"), F.call_function("div", F.col("id"), F.lit(64)).alias("y"))
    return bittree.test(_cells(spark, d, 2), probes, PARTS2)


@registered("bitcell_range", OCT_SQL + " SELECT x, y, z FROM cp WHERE x BETWEEN 3 AND 17 AND y BETWEEN 2 AND 6 AND z BETWEEN 0 AND 4")
def bitcell_range(spark: SparkSession, d: str) -> DataFrame:
    return bittree.report(_cells(spark, d, 3), (3, 2, 0, 17, 6, 4), PARTS2, 3)


# ---- baselines
ORDER = ("x", "y", "z", "pid")
BLOCK = 3000


def blocks_of(spark: SparkSession, d: str, name: str = "orders_span") -> baselines.Blocks:
    def make() -> baselines.Blocks:
        p, f = cloud(spark, d, name)
        return baselines.build_block_delta(p, f.parts(CONFIG), ("pid",), CLOUDS[name].attributes, BLOCK)

    return once(spark, ("blocks", d, name), make)


def _raw_of(spark: SparkSession, d: str) -> str:
    return once(spark, ("raw", d), lambda: baselines.write_raw(cloud(spark, d, "air")[0]))


registered("raw_roundtrip", W + grid_sql("air") + f" SELECT x, y, z, {ATTRS} FROM c")(lambda spark, d: baselines.read_raw(spark, _raw_of(spark, d)))
registered("raw_box", _box_sql("air", "third", ("intensity",)))(lambda spark, d: baselines.raw_scan(spark, _raw_of(spark, d), part_box(cloud(spark, d, "air")[1], *SINGLE["third"]), ["intensity"]))
BLOCKS_SQL = W + grid_sql("orders_span") + f", n AS (SELECT *, (row_number() OVER (ORDER BY pid) - 1) // {BLOCK} AS block FROM c)"


@registered("block_layout", BLOCKS_SQL + " SELECT CAST(block AS BIGINT) AS block, count(*) AS cnt, CAST(sum(x) AS BIGINT) AS sx, CAST(sum(z) AS BIGINT) AS sz FROM n GROUP BY block")
def block_layout(spark: SparkSession, d: str) -> DataFrame:
    p, _ = cloud(spark, d, "orders_span")
    return baselines.block_numbers(p, ("pid",), BLOCK).groupBy("block").agg(F.count("*").alias("cnt"), F.sum("x").alias("sx"), F.sum("z").alias("sz"))


@registered("quad_index", BLOCKS_SQL + " SELECT count(*) AS points, min(x) AS x_min, max(x) AS x_max, min(y) AS y_min, max(y) AS y_max, count(DISTINCT block) AS blocks FROM n")
def quad_index(spark: SparkSession, d: str) -> DataFrame:
    b = blocks_of(spark, d)
    c = b.cells().agg(F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"), F.min("y_min").alias("y_min"), F.max("y_max").alias("y_max"))
    n = b.cells().select(F.explode("blocks").alias("b")).agg(F.countDistinct("b").alias("blocks"))
    return b.blocks().agg(F.sum("cnt").alias("points")).crossJoin(c).crossJoin(n)  # one row each


registered("block_box", _box_sql("orders_span", "third"))(lambda spark, d: (lambda b, f: baselines.block_box(b, part_box(f, *SINGLE["third"])))(blocks_of(spark, d), cloud(spark, d, "orders_span")[1]))
registered("block_noindex", _box_sql("orders_span", "slab"))(lambda spark, d: (lambda b, f: baselines.block_box(b, part_box(f, *SINGLE["slab"]), use_index=False))(blocks_of(spark, d), cloud(spark, d, "orders_span")[1]))
registered("block_attr_box", _box_sql("air", "third", ("intensity",), " AND intensity BETWEEN 10 AND 20"))(lambda spark, d: (lambda b, f: baselines.block_box(b, part_box(f, *SINGLE["third"]), ["intensity"], _I))(blocks_of(spark, d, "air"), cloud(spark, d, "air")[1]))


@registered("block_work", BLOCKS_SQL + " SELECT CAST(count(DISTINCT block) AS BIGINT) AS blocks_decoded, count(*) AS points_decoded FROM n")
def block_work(spark: SparkSession, d: str) -> DataFrame:
    """A thin slab: every block of an order that is random in space has to be decoded."""
    return baselines.block_work(blocks_of(spark, d), part_box(cloud(spark, d, "orders_span")[1], *SINGLE["slab"]))


@registered("sorted_box", _box_sql("air", "third", ("intensity",)))
def sorted_box(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "air")
    path = once(spark, ("sorted", d), lambda: baselines.write_sorted(p, f.parts(CONFIG)))
    return baselines.sorted_parquet_box(spark, path, part_box(f, *SINGLE["third"]), ["intensity"])


# ---- measures
@registered("space_raw", W + grid_sql("air") + " SELECT count(*) AS points, count(*) * 20 AS bytes, CAST(ceil(count(*) * 20 / 1048576.0) AS BIGINT) AS mb FROM c")
def space_raw(spark: SparkSession, d: str) -> DataFrame:
    return measures.raw_space(cloud(spark, d, "air")[0])


@registered("space_components")
def space_components(spark: SparkSession, d: str) -> DataFrame:
    return measures.space(store_of(spark, d, "air"))


@registered("space_blocks")
def space_blocks(spark: SparkSession, d: str) -> DataFrame:
    return measures.block_space(blocks_of(spark, d, "air"))


@registered("bits_formula", _children_sql("flat", 100) + " SELECT (SELECT count(*) FROM boxes WHERE level < h) AS branch_bits, (SELECT count(*) FROM boxes WHERE NOT split) AS occupied_bits, (SELECT count(*) FROM c) AS tally_bits")
def bits_formula(spark: SparkSession, d: str) -> DataFrame:
    """Lengths of the three bitmaps from a census of nodes alone."""
    n, f = nodes_of(spark, d, "flat")
    h = len(f.parts(CONFIG))
    n = cut(n)
    inner = n.where(F.col("kind") == "branch")
    return inner.agg(F.count("*").alias("b"), F.count(F.when(F.col("level") == h - 1, 1)).alias("deep")).crossJoin(n.where("kind <> 'branch'").agg(F.sum("cnt").alias("tally_bits"))).select((8 + 8 * (F.col("b") - F.col("deep"))).alias("branch_bits"), (8 + 8 * F.col("b") - F.col("b")).alias("occupied_bits"), "tally_bits")


_PROFILED = ("air", "cube", "flat", "orders", "events", "embeddings", "grid")


@registered("cloud_profile", " UNION ALL ".join(f"(WITH {grid_sql(n)} SELECT '{n}' AS cloud, count(*) AS points, CAST(max(x) AS BIGINT) AS max_x, CAST(max(y) AS BIGINT) AS max_y, CAST(max(z) AS BIGINT) AS max_z FROM c)" for n in _PROFILED))
def cloud_profile(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for n in _PROFILED:
        p, _ = cloud(spark, d, n)
        r = measures.describe_cloud(clouds.load(spark, d, n), p, CLOUDS[n].policy.inverse).select(F.lit(n).alias("cloud"), "points", "max_x", "max_y", "max_z")
        out = r if out is None else out.unionByName(r)
    return out


@registered("density_grid", W + grid_sql("air") + " SELECT x // 500000 AS cx, y // 500000 AS cy, count(*) AS n FROM c GROUP BY 1, 2")
def density_grid(spark: SparkSession, d: str) -> DataFrame:
    return measures.density(cloud(spark, d, "air")[0], 500_000)


def _real(axis: str, c: str, null: int, *odd: tuple[int, str]) -> str:
    """A coordinate of customers that is null or not finite where the key modulo 6 says so."""
    return f"CASE c_custkey % 6 WHEN {null} THEN NULL " + "".join(f"WHEN {i} THEN CAST('{v}' AS DOUBLE) " for i, v in odd) + f"ELSE CAST({c} AS DOUBLE) END AS r{axis}"


_REALS = (_real("x", "c_acctbal", 1, (2, "NaN")), _real("y", "c_custkey", 9, (3, "Infinity")), _real("z", "c_nationkey", 9, (4, "-Infinity")))


@registered("rejects", f"SELECT count(*) FILTER (NOT ok) AS rejected, count(*) FILTER (ok) AS kept FROM (SELECT coalesce(isfinite(rx) AND isfinite(ry) AND isfinite(rz), false) AS ok FROM (SELECT {', '.join(_REALS)} FROM customer))")
def rejects(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.table(spark, d, "customer").selectExpr("c_custkey AS pid", *_REALS)
    return quantize.rejects(p).agg(F.count("*").alias("rejected")).crossJoin(p.where(quantize.valid(p)).agg(F.count("*").alias("kept")))  # one row each
