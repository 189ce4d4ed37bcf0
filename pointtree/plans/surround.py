"""Registered queries around the engine: joins, aggregates, windows, set operations, functions, SQL, UDFs, scans, stream-shaped plans."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import mlv
from ..functions.paths import common_levels, path_of
from ..operators import leaves, query
from ..operators.topology import ordered_index

from ..sources.clouds import grid_sql, table
from ..sources.shared import shared_dir
from ..streaming import ingest
from .book import CONFIG, cloud, leaves_of, sql_leaf_points, sql_points, store_of
from .book import query as registered
from .core import TILES_SQL, XYZ, tiled
from .workloads import BOXES_SQL, SINGLE, boxes, part_box, part_sql

W = "WITH "
AIR = W + grid_sql("air")
VOXEL = 400_000
div = lambda c, n: F.call_function("div", F.col(c), F.lit(n))
voxels = lambda: [div(a, VOXEL).alias(f"v{a}") for a in XYZ]
VOXELS_SQL = ", ".join(f"{a} // {VOXEL} AS v{a}" for a in "xyz")
INSIDE = " AND ".join(f"c.{a} BETWEEN b.{a}i AND b.{a}e" for a in "xyz")

def air(spark: SparkSession, d: str) -> DataFrame:
    return cloud(spark, d, "air")[0]

# ---- filters and scans
registered("filter_box", AIR + f" SELECT x, y, z FROM c WHERE {part_sql(*SINGLE['column'])}")(lambda spark, d: (lambda p, f: p.where(leaves.within(part_box(f, *SINGLE["column"]))).select(*XYZ))(*cloud(spark, d, "air")))

@registered("filter_or_boxes", AIR + f" SELECT x, y, z FROM c WHERE ({part_sql(*SINGLE['column'])}) OR ({part_sql(*SINGLE['small'])})")
def filter_or_boxes(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "air")
    return p.where(leaves.within(part_box(f, *SINGLE["column"])) | leaves.within(part_box(f, *SINGLE["small"]))).select(*XYZ)

registered("filter_class_in", AIR + " SELECT classification, count(*) AS n FROM c WHERE classification IN (1, 3) GROUP BY classification")(lambda spark, d: air(spark, d).where(F.col("classification").isin(1, 3)).groupBy("classification").agg(F.count("*").alias("n")))
registered("filter_null_attr", W + grid_sql("documents") + " SELECT pid, x, y, z FROM c WHERE quality IS NULL")(lambda spark, d: cloud(spark, d, "documents")[0].where(F.col("quality").isNull()).select("pid", *XYZ))
registered("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_orderkey < 5000")(lambda spark, d: table(spark, d, "lineitem").where("l_quantity >= 49 and l_orderkey < 5000").select("l_orderkey", "l_quantity"))

@registered("csv_roundtrip", W + grid_sql("orders") + " SELECT pid, x, y, z FROM c")
def csv_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    path = f"{shared_dir(spark)}/csv-{uuid.uuid4().hex}"
    cloud(spark, d, "orders")[0].select("pid", *XYZ).write.csv(path, header=True)
    return spark.read.schema("pid long, x long, y long, z long").csv(path, header=True, mode="PERMISSIVE")

@registered("json_roundtrip", W + grid_sql("parts") + " SELECT pid, x, y, z, brand FROM c")
def json_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    path = f"{shared_dir(spark)}/json-{uuid.uuid4().hex}"
    cloud(spark, d, "parts")[0].select("pid", *XYZ, "brand").write.json(path)
    return spark.read.schema("pid long, x long, y long, z long, brand int").json(path)

@registered("source_pushdown", AIR + f" SELECT x, y, z FROM c WHERE {part_sql(*SINGLE['third'])}")
def source_pushdown(spark: SparkSession, d: str) -> DataFrame:
    from ..sources import datasource

    s = store_of(spark, d, "air")
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(datasource.PointTreeSource)
    return spark.read.format("pointtree").option("path", s.path).load().where(leaves.within(part_box(s.frame, *SINGLE["third"]))).select(*XYZ)

# ---- joins
NATION_SQL = "JOIN supplier s ON c.point_source = s.s_suppkey JOIN nation n ON s.s_nationkey = n.n_nationkey JOIN region r ON n.n_regionkey = r.r_regionkey"

@registered("join_tiles", AIR + f" SELECT r_name, n_name, count(*) AS n, CAST(sum(intensity) AS BIGINT) AS total FROM c {NATION_SQL} GROUP BY r_name, n_name")
def join_tiles(spark: SparkSession, d: str) -> DataFrame:
    s, n, r = (table(spark, d, t) for t in ("supplier", "nation", "region"))
    j = air(spark, d).join(s, F.col("point_source") == F.col("s_suppkey")).join(n, F.col("s_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "n_name").agg(F.count("*").alias("n"), F.sum("intensity").alias("total"))

for _hint, _q in (("merge", "join_orders_smj"), ("shuffle_hash", "join_orders_shj")):
    def _join(spark: SparkSession, d: str, hint: str = _hint) -> DataFrame:
        li = table(spark, d, "lineitem").select("l_orderkey", F.col("l_quantity").cast("long").alias("intensity"))
        o = table(spark, d, "orders").select("o_orderkey", "o_orderstatus").hint(hint)
        return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("intensity").alias("total"))

    registered(_q, "SELECT o_orderstatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")(_join)

def join_boxes(leaf_rows: DataFrame, asked: DataFrame) -> DataFrame:
    """Leaves beside the boxes they meet, as an equi-join on cells: for more boxes than can be sent to all tasks.

    Cells come in classes of sides 2**k. A box or leaf whose widest axis fits a side of 2**k covers eight cells of that
    class at most; a pair meets in the larger class of the two, in the first cell that both cover.
    """
    def placed(rows: DataFrame, low, high, classes: list[int]) -> DataFrame:  # noqa: ANN001
        widest = F.greatest(*[high(a) - low(a) + 1 for a in XYZ])
        rows = rows.withColumn("own", F.ceil(F.log2(F.greatest(widest, F.lit(1)))).cast("int"))
        rows = rows.withColumn("k", F.explode(F.array_distinct(F.concat(F.array("own"), F.filter(F.array(*map(F.lit, classes)), lambda c: c > F.col("own"))))))
        for a in XYZ:
            rows = rows.withColumn(f"g{a}", F.explode(F.sequence(F.call_function("shiftright", low(a), F.col("k")), F.call_function("shiftright", high(a), F.col("k")))))
        return rows

    leaf_low, leaf_high = (lambda a: F.col(f"{a}0")), (lambda a: F.col(f"{a}0") + F.col("side") - 1)
    box_low, box_high = (lambda a: F.col(f"{a}i")), (lambda a: F.col(f"{a}e"))
    asked = asked.where(F.col("xi") <= F.col("xe")).where(F.col("yi") <= F.col("ye")).where(F.col("zi") <= F.col("ze"))
    of = lambda rows, low, high: sorted({r[0] for r in rows.select(F.ceil(F.log2(F.greatest(*[high(a) - low(a) + 1 for a in XYZ]))).cast("int")).distinct().collect()})  # noqa: E731  64 at most
    left = placed(leaf_rows, leaf_low, leaf_high, of(asked, box_low, box_high)).withColumnRenamed("own", "leaf_class")
    right = placed(asked, box_low, box_high, of(leaf_rows, leaf_low, leaf_high)).withColumnRenamed("own", "box_class")
    j = left.join(right, ["k", *[f"g{a}" for a in XYZ]]).where(F.col("k") == F.greatest("leaf_class", "box_class"))
    for a in XYZ:
        j = j.where((leaf_low(a) <= box_high(a)) & (leaf_high(a) >= box_low(a)))
        j = j.where(F.col(f"g{a}") == F.call_function("shiftright", F.greatest(leaf_low(a), box_low(a)), F.col("k")))
    return j.drop("k", "leaf_class", "box_class", *[f"g{a}" for a in XYZ])

def _all_boxes(spark: SparkSession, d: str) -> DataFrame:
    return boxes(spark, cloud(spark, d, "air")[1])

_ALL_SQL = f"WITH {grid_sql('air')}, {BOXES_SQL}, s AS (SELECT * FROM b)"

@registered("range_join_cells", _ALL_SQL + f" SELECT b.q, count(*) AS n FROM s b JOIN c ON {INSIDE} GROUP BY b.q")
def range_join_cells(spark: SparkSession, d: str) -> DataFrame:
    t, _ = leaves_of(spark, d, "air")
    met = join_boxes(t.select("level", "x0", "y0", "z0", "side", "xs", "ys", "zs"), _all_boxes(spark, d))
    p = met.select("q", *[f"{a}{e}" for a in XYZ for e in "ie"], "x0", "y0", "z0", F.explode(F.arrays_zip("xs", "ys", "zs")).alias("p"))
    for a in XYZ:
        p = p.where((F.col(f"{a}0") + F.coalesce(F.col(f"p.{a}s"), F.lit(0))).between(F.col(f"{a}i"), F.col(f"{a}e")))
    return p.groupBy("q").agg(F.count("*").alias("n"))

def _within_asked() -> F.Column:
    cond = F.lit(True)
    for a in XYZ:
        cond = cond & F.col(a).between(F.col(f"{a}i"), F.col(f"{a}e"))
    return cond

registered("range_join_bnlj", _ALL_SQL + f" SELECT b.q, count(*) AS n FROM s b JOIN c ON {INSIDE} GROUP BY b.q")(lambda spark, d: air(spark, d).join(F.broadcast(_all_boxes(spark, d)), _within_asked()).groupBy("q").agg(F.count("*").alias("n")))

@registered("box_batch_join", _ALL_SQL + f" SELECT b.q, CAST(sum(c.intensity) AS BIGINT) AS total FROM s b JOIN c ON {INSIDE} GROUP BY b.q")
def box_batch_join(spark: SparkSession, d: str) -> DataFrame:
    s = store_of(spark, d, "air")
    return query.points_in_boxes(s, _all_boxes(spark, d), columns=["intensity"]).groupBy("q").agg(F.sum("intensity").alias("total"))

def _counts_small(spark: SparkSession, d: str) -> DataFrame:
    s = store_of(spark, d, "air")
    return query.counts_in_boxes(s, _tiny(spark, d))

def _tiny(spark: SparkSession, d: str) -> DataFrame:
    """Boxes of a hundredth of each axis: most hold nothing."""
    b = boxes(spark, cloud(spark, d, "air")[1])
    return b.select("q", "xi", "yi", "zi", *[(F.col(f"{a}i") + div(f"{a}e", 100) - div(f"{a}i", 100)).alias(f"{a}e") for a in XYZ])

_TINY_SQL = f"WITH {grid_sql('air')}, {BOXES_SQL}, t AS (SELECT q, xi, yi, zi, " + ", ".join(f"{a}i + {a}e // 100 - {a}i // 100 AS {a}e" for a in "xyz") + f" FROM b), n AS (SELECT b.q, (SELECT count(*) FROM c WHERE {INSIDE}) AS n FROM t b)"
registered("box_semi", _TINY_SQL + " SELECT q FROM n WHERE n > 0")(lambda spark, d: _tiny(spark, d).join(_counts_small(spark, d).where("n > 0"), "q", "left_semi").select("q"))
registered("box_anti", _TINY_SQL + " SELECT q FROM n WHERE n = 0")(lambda spark, d: _tiny(spark, d).join(_counts_small(spark, d).where("n > 0"), "q", "left_anti").select("q"))
registered("box_left", _TINY_SQL + " SELECT q, n FROM n")(_counts_small)

@registered("cloud_diff_outer", f"WITH {grid_sql('air')}, t AS ({TILES_SQL}), p AS (SELECT {VOXELS_SQL}, tile FROM c JOIN t ON point_source = s_suppkey), a AS (SELECT vx, vy, vz, count(*) AS n FROM p WHERE tile < 4 GROUP BY ALL), b AS (SELECT vx, vy, vz, count(*) AS n FROM p WHERE tile BETWEEN 4 AND 8 GROUP BY ALL) SELECT vx, vy, vz, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM a FULL JOIN b USING (vx, vy, vz)")
def cloud_diff_outer(spark: SparkSession, d: str) -> DataFrame:
    t = tiled(spark, d).select(*voxels(), "tile")
    part = lambda c, n: t.where(c).groupBy("vx", "vy", "vz").agg(F.count("*").alias(n))
    j = part("tile < 4", "before").join(part("tile between 4 and 8", "after"), ["vx", "vy", "vz"], "full")
    zero = F.lit(0).cast("long")
    return j.select("vx", "vy", "vz", F.coalesce("before", zero).alias("before"), F.coalesce("after", zero).alias("after"))

@registered("asof_events", "WITH e AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view'), p AS (SELECT event_id AS pid, user_id, ts FROM events WHERE event_type = 'click') SELECT e.event_id, max_by(pid, (p.ts, pid)) AS nearest FROM e LEFT JOIN p ON p.user_id = e.user_id AND p.ts <= e.ts GROUP BY e.event_id")
def asof_events(spark: SparkSession, d: str) -> DataFrame:
    """The latest click up to each view of a user: one window over both kinds, no join of pairs."""
    e = table(spark, d, "events").where("event_type in ('view', 'click')")
    w = Window.partitionBy("user_id").orderBy("ts", (F.col("event_type") == "view").cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("nearest", last).where("event_type = 'view'").select("event_id", "nearest")

@registered("interval_events", "SELECT p.event_id AS purchase, count(*) AS near FROM events p JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts BETWEEN p.ts - INTERVAL 600 SECOND AND p.ts + INTERVAL 600 SECOND WHERE p.event_type = 'purchase' GROUP BY p.event_id")
def interval_events(spark: SparkSession, d: str) -> DataFrame:
    """Views within ten minutes of a purchase: both sides in buckets of ten minutes, the purchase in three."""
    e = table(spark, d, "events").withColumn("s", F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01', ts)"))
    bucket = F.floor(F.col("s") / 600)
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("at"), F.explode(F.sequence(bucket - 1, bucket + 1)).alias("b"))
    v = e.where("event_type = 'view'").select("user_id", "ts", bucket.alias("b"))
    near = F.expr("ts between at - interval 600 seconds and at + interval 600 seconds")
    return p.join(v, ["user_id", "b"]).where(near).groupBy("purchase").agg(F.count("*").alias("near"))

@registered("cross_boxes", f"WITH {grid_sql('air')}, {BOXES_SQL} SELECT q, axis, CASE axis WHEN 'x' THEN xe - xi WHEN 'y' THEN ye - yi ELSE ze - zi END AS width FROM b, (VALUES ('x'), ('y'), ('z')) a(axis)")
def cross_boxes(spark: SparkSession, d: str) -> DataFrame:
    """Boxes beside the three axes, a constant."""
    b = boxes(spark, cloud(spark, d, "air")[1])
    e = F.explode(F.array(*[F.struct(F.lit(a).alias("axis"), (F.col(f"{a}e") - F.col(f"{a}i")).alias("width")) for a in XYZ])).alias("w")
    return b.select("q", e).select("q", "w.axis", "w.width")

# ---- aggregation
registered("voxel_stats", AIR + f" SELECT {VOXELS_SQL}, count(*) AS n, min(intensity) AS lo, max(intensity) AS hi, CAST(sum(intensity) AS BIGINT) AS total FROM c GROUP BY 1, 2, 3")(lambda spark, d: air(spark, d).groupBy(*voxels()).agg(F.count("*").alias("n"), F.min("intensity").alias("lo"), F.max("intensity").alias("hi"), F.sum("intensity").alias("total")))
registered("distinct_cells", W + grid_sql("grid") + " SELECT DISTINCT x, y, z FROM c")(lambda spark, d: cloud(spark, d, "grid")[0].select(*XYZ).distinct())
registered("approx_cells")(lambda spark, d: cloud(spark, d, "grid")[0].agg(F.approx_count_distinct(F.struct(*XYZ), 0.02).alias("cells")))
registered("approx_intensity")(lambda spark, d: air(spark, d).groupBy("classification").agg(F.percentile_approx("intensity", 0.5, 1000).alias("median")))
registered("gsets_class", AIR + f", t AS ({TILES_SQL}) SELECT classification, tile, count(*) AS n FROM c JOIN t ON point_source = s_suppkey GROUP BY GROUPING SETS ((classification, tile), (classification), ())")(lambda spark, d: tiled(spark, d).groupingSets([["classification", "tile"], ["classification"], []], "classification", "tile").agg(F.count("*").alias("n")))
registered("rollup_zone", W + sql_points("air") + " SELECT substr(path, 1, 1) AS a, substr(path, 1, 2) AS b, count(*) AS n FROM pts GROUP BY ROLLUP (substr(path, 1, 1), substr(path, 1, 2))")(lambda spark, d: (lambda p, f: p.withColumn("path", path_of(f.parts(CONFIG))).rollup(F.substring("path", 1, 1).alias("a"), F.substring("path", 1, 2).alias("b")).agg(F.count("*").alias("n")))(*cloud(spark, d, "air")))
registered("cube_class", AIR + " SELECT classification, return_number, count(*) AS n FROM c GROUP BY CUBE (classification, return_number)")(lambda spark, d: air(spark, d).cube("classification", "return_number").agg(F.count("*").alias("n")))
registered("pivot_returns", AIR + " SELECT return_number, count(*) FILTER (classification = 1) AS c1, count(*) FILTER (classification = 2) AS c2, count(*) FILTER (classification = 3) AS c3 FROM c GROUP BY return_number")(lambda spark, d: air(spark, d).groupBy("return_number").pivot("classification", [1, 2, 3]).count().select("return_number", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"c{i}") for i in (1, 2, 3)]))
registered("having_dense", AIR + f" SELECT {VOXELS_SQL}, count(*) AS n FROM c GROUP BY 1, 2, 3 HAVING count(*) > 100")(lambda spark, d: air(spark, d).groupBy(*voxels()).agg(F.count("*").alias("n")).where("n > 100"))
registered("agg_filter", AIR + " SELECT point_source, count(*) FILTER (scan_angle < 0) AS left_, CAST(sum(intensity) FILTER (edge_of_flight_line = 1) AS BIGINT) AS edge FROM c GROUP BY point_source")(lambda spark, d: air(spark, d).groupBy("point_source").agg(F.count(F.when(F.col("scan_angle") < 0, 1)).alias("left_"), F.sum(F.when(F.col("edge_of_flight_line") == 1, F.col("intensity"))).alias("edge")))
registered("top_intensity", W + grid_sql("events") + " SELECT event_code, max_by(pid, (z, pid)) AS pid, max(z) AS z FROM c GROUP BY event_code")(lambda spark, d: cloud(spark, d, "events")[0].groupBy("event_code").agg(F.max_by("pid", F.struct("z", "pid")).alias("pid"), F.max("z").alias("z")))
registered("bit_or_flags", AIR + " SELECT point_source, bit_or(1 << classification) AS classes, bit_or(1 << return_number) AS returns FROM c GROUP BY point_source")(lambda spark, d: air(spark, d).groupBy("point_source").agg(F.bit_or(F.expr("shiftleft(1, classification)")).alias("classes"), F.bit_or(F.expr("shiftleft(1, return_number)")).alias("returns")))

# ---- windows
registered("win_positions", W + sql_points("orders") + " SELECT pid, CAST(row_number() OVER (PARTITION BY substr(path, 1, 4) ORDER BY path, pid) AS BIGINT) AS place FROM pts")(lambda spark, d: (lambda p, f: p.withColumn("path", path_of(f.parts(CONFIG))).select("pid", F.row_number().over(Window.partitionBy(F.substring("path", 1, 4)).orderBy("path", "pid")).cast("long").alias("place")))(*cloud(spark, d, "orders")))
_we = lambda: Window.partitionBy("event_code").orderBy("z", "pid")
registered("win_rank", W + grid_sql("events") + " SELECT pid, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY event_code ORDER BY z) AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS quarter FROM c WINDOW w AS (PARTITION BY event_code ORDER BY z, pid)")(lambda spark, d: cloud(spark, d, "events")[0].select("pid", F.rank().over(_we()).cast("long").alias("r"), F.dense_rank().over(Window.partitionBy("event_code").orderBy("z")).cast("long").alias("dr"), F.ntile(4).over(_we()).cast("long").alias("quarter")))
registered("win_running", W + grid_sql("events") + " SELECT pid, CAST(sum(z) OVER (PARTITION BY event_code ORDER BY x, pid) AS BIGINT) AS total FROM c")(lambda spark, d: cloud(spark, d, "events")[0].select("pid", F.sum("z").over(Window.partitionBy("event_code").orderBy("x", "pid")).alias("total")))
registered("win_range", W + grid_sql("events") + " SELECT pid, count(*) OVER (PARTITION BY event_code ORDER BY x RANGE BETWEEN 3600 PRECEDING AND 3600 FOLLOWING) AS near FROM c")(lambda spark, d: cloud(spark, d, "events")[0].select("pid", F.count("*").over(Window.partitionBy("event_code").orderBy("x").rangeBetween(-3600, 3600)).alias("near")))
registered("win_first_last", W + grid_sql("events") + " SELECT DISTINCT y, first_value(pid) OVER w AS first_, last_value(pid) OVER w AS last_ FROM c WINDOW w AS (PARTITION BY y ORDER BY x, pid ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda spark, d: cloud(spark, d, "events")[0].select("y", *[f("pid").over(Window.partitionBy("y").orderBy("x", "pid").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for f, n in ((F.first, "first_"), (F.last, "last_"))]).distinct())
registered("win_percent", W + grid_sql("parts") + " SELECT pid, CAST(round(1000 * percent_rank() OVER (PARTITION BY brand ORDER BY y, pid)) AS BIGINT) AS pm FROM c")(lambda spark, d: cloud(spark, d, "parts")[0].select("pid", F.round(1000 * F.percent_rank().over(Window.partitionBy("brand").orderBy("y", "pid"))).cast("long").alias("pm")))

# ---- order, limits, sets, subqueries, samples
registered("sort_path", W + sql_points("orders") + " SELECT pid, path, CAST(row_number() OVER (ORDER BY path, pid) - 1 AS BIGINT) AS pos FROM pts")(lambda spark, d: (lambda p, f: ordered_index(p.select("pid", path_of(f.parts(CONFIG)).alias("path")), "path", "pid"))(*cloud(spark, d, "orders")))
registered("topk_per_voxel", W + grid_sql("events") + " SELECT event_code, pid, z FROM (SELECT *, row_number() OVER (PARTITION BY event_code ORDER BY z DESC, pid) AS r FROM c) WHERE r <= 5")(lambda spark, d: cloud(spark, d, "events")[0].withColumn("r", F.row_number().over(Window.partitionBy("event_code").orderBy(F.desc("z"), "pid"))).where("r <= 5").select("event_code", "pid", "z"))
registered("topk_global", W + grid_sql("orders") + " SELECT pid, y FROM c ORDER BY y DESC, pid LIMIT 25")(lambda spark, d: cloud(spark, d, "orders")[0].select("pid", "y").orderBy(F.desc("y"), "pid").limit(25))
_SETS = f"WITH {grid_sql('air')}, t AS ({TILES_SQL}), p AS (SELECT {VOXELS_SQL}, tile FROM c JOIN t ON point_source = s_suppkey), a AS (SELECT vx, vy, vz FROM p WHERE tile < 4), b AS (SELECT vx, vy, vz FROM p WHERE tile BETWEEN 4 AND 8)"

def _two(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    t = tiled(spark, d).select(*voxels(), "tile")
    return t.where("tile < 4").drop("tile"), t.where("tile between 4 and 8").drop("tile")

registered("union_cells", _SETS + " SELECT * FROM a UNION SELECT * FROM b")(lambda spark, d: (lambda a, b: a.union(b).distinct())(*_two(spark, d)))
registered("intersect_cells", _SETS + " SELECT * FROM a INTERSECT SELECT * FROM b")(lambda spark, d: (lambda a, b: a.intersect(b))(*_two(spark, d)))
registered("except_cells", _SETS + " SELECT * FROM a EXCEPT SELECT * FROM b")(lambda spark, d: (lambda a, b: a.subtract(b))(*_two(spark, d)))
registered("except_all", _SETS + " SELECT * FROM a EXCEPT ALL SELECT * FROM b")(lambda spark, d: (lambda a, b: a.exceptAll(b))(*_two(spark, d)))

def _views(spark: SparkSession, d: str) -> None:
    p, f = cloud(spark, d, "air")
    p.createOrReplaceTempView("points")
    leaves_of(spark, d, "air")[0].createOrReplaceTempView("leaves")
    store_of(spark, d, "air").shards().createOrReplaceTempView("shards")
    boxes(spark, f).createOrReplaceTempView("boxes")

def _sql(text: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        _views(spark, d)
        return spark.sql(text)

    return run

_LEAF = W + sql_leaf_points("air") + ", leaves AS (SELECT level, leaf AS path, count(*) AS cnt FROM lp GROUP BY level, leaf)"
registered("sub_scalar", _LEAF + " SELECT path, cnt FROM leaves WHERE cnt > 2 * (SELECT avg(cnt) FROM leaves)")(_sql("select path, cnt from leaves where cnt > 2 * (select avg(cnt) from leaves)"))
registered("sub_in", _LEAF + " SELECT path, cnt FROM leaves WHERE level IN (SELECT min(level) FROM leaves)")(_sql("select path, cnt from leaves where level in (select min(level) from leaves)"))
registered("sub_exists", AIR + " SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM c WHERE point_source = s_suppkey AND intensity = 50 AND scan_angle = 5)")(lambda spark, d: (_views(spark, d), table(spark, d, "supplier").createOrReplaceTempView("suppliers"), spark.sql("select s_suppkey from suppliers where exists (select 1 from points where point_source = s_suppkey and intensity = 50 and scan_angle = 5)"))[2])
registered("voxel_thin", W + grid_sql("events") + " SELECT min(pid) AS pid FROM c GROUP BY x // 100000, y // 20, z // 10000")(lambda spark, d: cloud(spark, d, "events")[0].groupBy(div("x", 100_000), div("y", 20), div("z", 10_000)).agg(F.min("pid").alias("pid")).select("pid"))

def _box_text(spark: SparkSession, d: str, part: str) -> str:
    b = part_box(cloud(spark, d, "air")[1], *SINGLE[part])
    return " and ".join(f"{a} between {b[i]} and {b[i + 3]}" for i, a in enumerate(XYZ))

def sql_box(spark: SparkSession, d: str, more: str = "") -> DataFrame:
    """The box query as SQL over the leaf view."""
    _views(spark, d)
    b = part_box(cloud(spark, d, "air")[1], *SINGLE["third"])
    meets = " and ".join(f"{a}0 <= {b[i + 3]} and {a}0 + side > {b[i]}" for i, a in enumerate(XYZ))
    inner = f"select x0 + p.xs as x, y0 + p.ys as y, z0 + p.zs as z, p.a_intensity as intensity from leaves lateral view explode(arrays_zip(xs, ys, zs, a_intensity)) e as p where {meets}"
    return spark.sql(f"select x, y, z, intensity from ({inner}) where {_box_text(spark, d, 'third')}{more}")

_THIRD = f" SELECT x, y, z, intensity FROM c WHERE {part_sql(*SINGLE['third'])}"
registered("sql_box", AIR + _THIRD)(lambda spark, d: sql_box(spark, d))
registered("sql_attr_box", AIR + _THIRD + " AND intensity BETWEEN 10 AND 20")(lambda spark, d: sql_box(spark, d, " and intensity between 10 and 20"))

registered("sql_count", AIR + f" SELECT count(*) AS n FROM c WHERE {part_sql(*SINGLE['third'])}")(lambda spark, d: (sql_box(spark, d).createOrReplaceTempView("found"), spark.sql("select count(*) as n from found"))[1])

@registered("sql_slab", AIR + f" SELECT x, y, z FROM c WHERE {part_sql(*SINGLE['slab'])}")
def sql_slab(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d)
    b = part_box(cloud(spark, d, "air")[1], *SINGLE["slab"])
    inner = f"select x0 + p.xs as x, y0 + p.ys as y, z0 + p.zs as z from leaves lateral view explode(arrays_zip(xs, ys, zs)) e as p where z0 <= {b[5]} and z0 + side > {b[2]}"
    return spark.sql(f"select x, y, z from ({inner}) where z between {b[2]} and {b[5]}")

def box_points(spark: SparkSession) -> None:
    """Registers the table function ``box_points``: points of a shard's components in a grid box, for SQL."""
    from ..operators import shards as kernel

    @F.udtf(returnType="x long, y long, z long")
    class BoxPoints:
        def eval(self, row: dict, xi: int, yi: int, zi: int, xe: int, ye: int, ze: int):
            r = row.asDict()
            o = [r[f"{a}0"] for a in "xyz"]
            got = kernel.scan(kernel.from_row({k: bytes(v) if isinstance(v, (bytes, bytearray)) else v for k, v in r.items()}), (xi - o[0], yi - o[1], zi - o[2], xe - o[0], ye - o[1], ze - o[2]))
            for x, y, z in zip(*[(got[a] + o[i]).tolist() for i, a in enumerate("xyz")], strict=True):
                yield x, y, z

    spark.udtf.register("box_points", BoxPoints)

@registered("sql_box_points", AIR + f" SELECT x, y, z FROM c WHERE {part_sql(*SINGLE['third'])}")
def sql_box_points(spark: SparkSession, d: str) -> DataFrame:
    """The box query as SQL over packed shards, by a table function beside each shard that the box meets."""
    _views(spark, d)
    box_points(spark)
    b = part_box(cloud(spark, d, "air")[1], *SINGLE["third"])
    meets = " and ".join(f"s.{a}_min <= {b[i + 3]} and s.{a}_max >= {b[i]}" for i, a in enumerate(XYZ))
    row = "struct(s.x0, s.y0, s.z0, s.parts, s.leaf_order, s.root_leaf, s.t_branch, s.t_occupied, s.t_tally, s.c_x, s.c_y, s.c_z)"
    return spark.sql(f"select p.x, p.y, p.z from (select * from shards s where {meets}) s, lateral box_points({row}, {', '.join(map(str, b))}) p")

# ---- functions
registered("fn_math", W + grid_sql("orders") + " SELECT pid, CAST(floor(y / 7.0) AS BIGINT) AS f, CAST(ceil(y / 7.0) AS BIGINT) AS c, y // 13 AS d, y % 13 AS r, CAST(bit_count(y) AS INTEGER) AS ones, x << 3 AS up, greatest(x, z) AS big, least(x, z) AS small, CAST(round(sqrt(x * x + z * z)) AS BIGINT) AS dist FROM c")(lambda spark, d: cloud(spark, d, "orders")[0].select("pid", F.floor(F.col("y") / 7.0).alias("f"), F.ceil(F.col("y") / 7.0).alias("c"), div("y", 13).alias("d"), (F.col("y") % 13).alias("r"), F.bit_count("y").alias("ones"), F.shiftleft("x", 3).alias("up"), F.greatest("x", "z").alias("big"), F.least("x", "z").alias("small"), F.round(F.sqrt(F.col("x") * F.col("x") + F.col("z") * F.col("z"))).cast("long").alias("dist")))

@registered("fn_path", W + sql_points("orders") + ", n AS (SELECT pid, path, h, lead(path) OVER (ORDER BY pid) AS nxt FROM pts) SELECT pid, substr(path, 1, 5) AS head, CAST(instr(path, '7') AS INTEGER) AS seven, rpad(substr(path, 1, 3), 8, '*') AS pad, translate(substr(path, 1, 6), '01', 'ab') AS named, CAST((SELECT coalesce(max(i), 0) FROM range(1, 40) r(i) WHERE i <= h AND substr(path, 1, i) = substr(nxt, 1, i)) AS INTEGER) AS common FROM n WHERE nxt IS NOT NULL")
def fn_path(spark: SparkSession, d: str) -> DataFrame:
    """Each path beside the next one; the next row is found by its place in the order, which ranges give."""
    p, f = cloud(spark, d, "orders")
    parts = f.parts(CONFIG)
    p = ordered_index(p.select("pid", *XYZ), "pid", name="at")
    far = p.withColumn("path", path_of(parts)).join(p.select((F.col("at") - 1).alias("at"), *[F.col(a).alias(f"n{a}") for a in XYZ]), "at")
    return far.select("pid", F.substring("path", 1, 5).alias("head"), F.instr("path", "7").alias("seven"), F.rpad(F.substring("path", 1, 3), 8, "*").alias("pad"), F.translate(F.substring("path", 1, 6), "01", "ab").alias("named"), common_levels(tuple(map(F.col, XYZ)), (F.col("nx"), F.col("ny"), F.col("nz")), parts).alias("common"))

registered("fn_time", "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(extract(year FROM o_orderdate) AS INTEGER) AS y, CAST(date_diff('day', CAST(date_trunc('month', o_orderdate) AS DATE), CAST(o_orderdate AS DATE)) AS INTEGER) AS dom FROM orders")(lambda spark, d: table(spark, d, "orders").select("o_orderkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("y"), F.datediff(F.col("o_orderdate").cast("date"), F.trunc(F.col("o_orderdate").cast("date"), "month")).alias("dom")))

@registered("fn_array", "WITH e AS (SELECT vec_id, list_transform(embedding, lambda v: CAST(round(CAST(v AS DOUBLE) * 1000) AS BIGINT)) AS a FROM embeddings) SELECT vec_id, CAST(list_sum(a) AS BIGINT) AS total, CAST(len(list_filter(a, lambda v: v > 100)) AS INTEGER) AS big, a[3] AS third, CAST(list_sum(a[5:8]) AS BIGINT) AS middle FROM e")
def fn_array(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: F.round(v.cast("double") * 1000).cast("long")).alias("a"))
    total = lambda c: F.aggregate(c, F.lit(0).cast("long"), lambda s, v: s + v)
    return a.select("vec_id", total("a").alias("total"), F.size(F.filter("a", lambda v: v > 100)).alias("big"), F.element_at("a", 3).alias("third"), total(F.slice("a", 5, 4)).alias("middle"))

@registered("fn_map", AIR + " SELECT point_source, intensity, user_data, CAST((intensity > 25) AS INTEGER) + CAST((user_data > 25) AS INTEGER) AS over FROM c")
def fn_map(spark: SparkSession, d: str) -> DataFrame:
    m = air(spark, d).select("point_source", F.map_from_arrays(F.array(F.lit("intensity"), F.lit("user_data")), F.array("intensity", "user_data")).alias("m"))
    return m.select("point_source", F.element_at("m", "intensity").alias("intensity"), F.element_at("m", "user_data").alias("user_data"), F.size(F.map_filter("m", lambda k, v: v > 25)).alias("over"))

registered("fn_struct", f"WITH {grid_sql('air')}, {BOXES_SQL} SELECT q, xi, ye, (xe - xi) * 2 AS twice FROM b")(lambda spark, d: boxes(spark, cloud(spark, d, "air")[1]).select("q", F.struct("xi", "xe", "ye").alias("b")).select("q", F.col("b.xi").alias("xi"), F.col("b.ye").alias("ye"), ((F.col("b.xe") - F.col("b.xi")) * 2).alias("twice")))
registered("fn_json", "SELECT event_id, CAST(props->>'$.k' AS INTEGER) AS k, CAST(props->>'$.k' AS INTEGER) + 1 AS k1 FROM events")(lambda spark, d: table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), (F.from_json("props", "k int")["k"] + 1).alias("k1")))
registered("fn_null", W + grid_sql("documents") + " SELECT pid, coalesce(toxic, -1) AS t, nullif(quality, 0) AS q, CASE WHEN quality IS NULL THEN 'none' WHEN quality = 1 THEN 'good' ELSE 'bad' END AS named FROM c")(lambda spark, d: cloud(spark, d, "documents")[0].select("pid", F.coalesce("toxic", F.lit(-1)).alias("t"), F.nullif(F.col("quality"), F.lit(0)).alias("q"), F.when(F.col("quality").isNull(), "none").when(F.col("quality") == 1, "good").otherwise("bad").alias("named")))
registered("fn_binary", W + sql_points("parts") + " SELECT pid, hex(path) AS h, CAST(octet_length(encode(path)) AS INTEGER) AS n FROM pts")(lambda spark, d: (lambda p, f: p.withColumn("path", path_of(f.parts(CONFIG))).select("pid", F.hex(F.unhex(F.hex("path"))).alias("h"), F.octet_length(F.col("path").cast("binary")).alias("n")))(*cloud(spark, d, "parts")))

# ---- user-defined functions
@registered("udf_mlv_bits")
def udf_mlv_bits(spark: SparkSession, d: str) -> DataFrame:
    """Bits of each leaf's coordinate code."""
    @F.pandas_udf("long")
    def bits(a: pd.Series) -> pd.Series:
        return a.map(lambda v: mlv.encode(np.asarray(v, np.uint64)).bits)

    t, _ = leaves_of(spark, d, "air")
    return t.select("path", bits("xs").alias("bits_x"))

@registered("udf_decode_leaf", W + sql_leaf_points("air") + " SELECT " + ", ".join(f"CAST(sum(l{a}) AS BIGINT) AS sum_{a}" for a in "xyz") + ", count(lx) AS stored FROM lp")
def udf_decode_leaf(spark: SparkSession, d: str) -> DataFrame:
    """Coordinates of leaves out of the stored codes, shard by shard, as arrays."""
    @F.arrow_udf("array<long>")
    def decode_leaf(code: pa.Array) -> pa.Array:
        return pa.array([m.slice(0, m.n).astype(np.int64) for m in map(mlv.Mlv.from_bytes, code.to_pylist())], pa.list_(pa.int64()))

    got = store_of(spark, d, "air").shards().select(*[decode_leaf(f"c_{a}").alias(a) for a in XYZ])
    total = lambda a: F.aggregate(a, F.lit(0).cast("long"), lambda s, v: s + v)
    return got.agg(*[F.sum(total(a)).alias(f"sum_{a}") for a in XYZ], F.sum(F.size("x")).alias("stored"))

@registered("udaf_bitlen", W + grid_sql("orders") + " SELECT CAST(length(bin(y)) AS BIGINT) AS bits, count(*) AS n FROM c GROUP BY 1")
def udaf_bitlen(spark: SparkSession, d: str) -> DataFrame:
    """The histogram of bit lengths by Arrow batches with partial sums, then one small aggregate."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(65, np.int64)
        for b in batches:
            total += np.bincount(mlv.bit_lengths(b.column(0).to_numpy()), minlength=65)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["bits", "n"])

    return cloud(spark, d, "orders")[0].select("y").mapInArrow(run, "bits long, n long").groupBy("bits").agg(F.sum("n").alias("n"))

@registered("udtf_boxes", f"WITH {grid_sql('air')}, {BOXES_SQL} SELECT q, xi, xe FROM b")
def udtf_boxes(spark: SparkSession, d: str) -> DataFrame:
    f = cloud(spark, d, "air")[1]

    @F.udtf(returnType="q long, xi long, xe long")
    class Boxes:
        def eval(self, n: int, extent: int):
            sizes = (100, 150, 200, 250, 300, 400, 500, 600, 800, 1000)
            for q in range(n):
                low = (q * 389 + 13) % 1009 * extent // 1009
                yield q, low, min(low + extent * sizes[q % 10] // 1000, extent)

    return Boxes(F.lit(500), F.lit(f.extent[0]))

# ---- stream-shaped plans, run as batches, and streams
_EV = "SELECT *, user_id // 10 AS zone FROM events"
registered("win_tumbling", f"WITH e AS ({_EV}) SELECT zone, CAST(date_diff('second', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS BIGINT) AS at, count(*) AS n FROM e GROUP BY 1, 2")(lambda spark, d: ingest.tumbling(ingest.zoned(table(spark, d, "events")), "1 hour"))
registered("win_sliding", f"WITH e AS ({_EV}), w AS (SELECT zone, date_diff('second', TIMESTAMP '2024-01-01', date_trunc('second', ts)) // 1800 AS b FROM e), x AS (SELECT zone, b - unnest(range(4)) AS b FROM w) SELECT zone, CAST(b * 1800 AS BIGINT) AS at, count(*) AS n FROM x GROUP BY 1, 2")(lambda spark, d: ingest.tumbling(ingest.zoned(table(spark, d, "events")), "2 hours", "30 minutes"))
registered("win_session", "WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM e) SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, no, count(*) AS n FROM s GROUP BY 1, 2) GROUP BY 1, 2")(lambda spark, d: ingest.sessions(table(spark, d, "events")).groupBy("user_id", "n").agg(F.count("*").alias("sessions")))
registered("stream_static", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY c_mktsegment")(ingest.stream_static)
registered("stream_late", "WITH e AS (SELECT user_id // 10 AS zone, date_trunc('hour', ts) AS w FROM events), g AS (SELECT zone, w, count(*) AS n FROM e GROUP BY 1, 2) SELECT zone, n FROM g WHERE w + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")(ingest.stream_late)
registered("stream_dedup", "SELECT CAST(count(DISTINCT event_id) AS BIGINT) AS n FROM events")(ingest.stream_dedup)
registered("stream_split", "SELECT zone, n, CAST(n > 100 AS BOOLEAN) AS divide FROM (SELECT user_id // 10 AS zone, count(*) AS n FROM events GROUP BY 1)")(ingest.stream_split)
registered("stream_ingest", W + grid_sql("events") + " SELECT x, y, z, event_code FROM c WHERE x BETWEEN 500000 AND 1500000")(ingest.stream_ingest)
