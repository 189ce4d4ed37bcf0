"""Point clouds on the given tables, each with its SQL counterpart.

A cloud is ``pid, rx, ry, rz`` and attribute columns. Attributes follow the public point record format 0.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.quantize import Fixed, Frame, Span, apply, fit_frame

RECORD0 = ["intensity", "return_number", "number_of_returns", "scan_direction", "edge_of_flight_line", "classification", "scan_angle", "user_data", "point_source"]
#: Converted extents of the flagship cloud, wide in x and y and thin in z.
AIR = (3_999_990, 3_999_990, 218_720)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class Cloud:
    load: Callable[[SparkSession, str], DataFrame]
    policy: Fixed | Span
    attributes: tuple[str, ...]
    sql: str  # SELECT giving pid, integers rx, ry, rz after the inverse scale, and attributes
    tiles: int | None = None  # points of tiles below this alone, on the grid of all


def _days(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit("1995-01-01").cast("date"))


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem")
    i = lambda c: c.cast("int")
    return t.select(
        F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("pid"),
        F.col("l_orderkey").cast("double").alias("rx"), F.col("l_extendedprice").alias("ry"), _days("l_shipdate").cast("double").alias("rz"),
        i(F.col("l_quantity")).alias("intensity"), F.col("l_linenumber").alias("return_number"),
        F.max("l_linenumber").over(Window.partitionBy("l_orderkey")).alias("number_of_returns"),
        i(F.col("l_linestatus") == "O").alias("scan_direction"), i(F.col("l_discount") == 0).alias("edge_of_flight_line"),
        i(F.translate("l_returnflag", "ANR", "123")).alias("classification"), i(F.round(F.col("l_discount") * 100) - 5).alias("scan_angle"),
        i(F.round(F.col("l_tax") * 100)).alias("user_data"), i(F.col("l_suppkey")).alias("point_source"))


LINEITEM_SQL = """SELECT 0 AS pid, l_orderkey AS rx, CAST(round(l_extendedprice * 100) AS BIGINT) AS ry, CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS BIGINT) AS rz,
CAST(l_quantity AS INTEGER) AS intensity, l_linenumber AS return_number, max(l_linenumber) OVER (PARTITION BY l_orderkey) AS number_of_returns, CAST(l_linestatus = 'O' AS INTEGER) AS scan_direction,
CAST(l_discount = 0 AS INTEGER) AS edge_of_flight_line, CAST(translate(l_returnflag, 'ANR', '123') AS INTEGER) AS classification, CAST(round(l_discount * 100) - 5 AS INTEGER) AS scan_angle,
CAST(round(l_tax * 100) AS INTEGER) AS user_data, CAST(l_suppkey AS INTEGER) AS point_source FROM lineitem"""


def grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("pid"), F.col("l_quantity").alias("rx"), F.col("l_discount").alias("ry"), F.col("l_tax").alias("rz"), F.col("l_linenumber").alias("return_number"))


GRID_SQL = "SELECT 0 AS pid, CAST(round(l_quantity) AS BIGINT) AS rx, CAST(round(l_discount * 100) AS BIGINT) AS ry, CAST(round(l_tax * 100) AS BIGINT) AS rz, l_linenumber AS return_number FROM lineitem"


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("pid"), F.col("o_custkey").cast("double").alias("rx"), F.col("o_totalprice").alias("ry"), _days("o_orderdate").cast("double").alias("rz"))


ORDERS_SQL = "SELECT o_orderkey AS pid, o_custkey AS rx, CAST(round(o_totalprice * 100) AS BIGINT) AS ry, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS rz FROM orders"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    code = F.expr("case event_type " + " ".join(f"when '{k}' then {i}" for i, k in enumerate(EVENT_TYPES, 1)) + " else 0 end").cast("int")
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("pid"), F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01', ts)").cast("double").alias("rx"), F.col("user_id").cast("double").alias("ry"), F.col("value").alias("rz"), code.alias("event_code"), F.get_json_object("props", "$.k").cast("int").alias("prop"))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
EVENTS_SQL = "SELECT event_id AS pid, date_diff('second', TIMESTAMP '2024-01-01', date_trunc('second', ts)) AS rx, user_id AS ry, CAST(round(value * 100) AS BIGINT) AS rz, CASE event_type " + " ".join(f"WHEN '{k}' THEN {i}" for i, k in enumerate(EVENT_TYPES, 1)) + " ELSE 0 END AS event_code, CAST(props->>'$.k' AS INTEGER) AS prop FROM events"


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = lambda i: F.col("embedding")[i].cast("double")
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), c(0).alias("rx"), c(1).alias("ry"), c(2).alias("rz"), "label")


EMBEDDINGS_SQL = "SELECT vec_id AS pid, " + ", ".join(f"CAST(round(CAST(embedding[{i + 1}] AS DOUBLE) * 1000000) AS BIGINT) AS r{a}" for i, a in enumerate("xyz")) + ", label FROM embeddings"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths of texts with two bits that cover some of them only."""
    d = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    spaces = F.length("text") - F.length(F.replace(F.col("text"), F.lit(" "), F.lit("")))
    lang = F.expr("case lang when 'de' then 1 when 'en' then 2 when 'es' then 3 when 'fr' then 4 else 0 end")
    return d.select(F.col("doc_id").alias("pid"), F.col("doc_id").cast("double").alias("rx"), F.col("n_chars").cast("double").alias("ry"), spaces.cast("double").alias("rz"), "quality", "toxic", lang.cast("int").alias("lang_code"), F.regexp_extract("source", r"(\d+)$", 1).try_cast("int").alias("source_code"))


DOCUMENTS_SQL = "SELECT d.doc_id AS pid, d.doc_id AS rx, n_chars AS ry, length(text) - length(replace(text, ' ', '')) AS rz, quality, toxic, CASE lang WHEN 'de' THEN 1 WHEN 'en' THEN 2 WHEN 'es' THEN 3 WHEN 'fr' THEN 4 ELSE 0 END AS lang_code, TRY_CAST(regexp_extract(source, '(\\d+)$', 1) AS INTEGER) AS source_code FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id"


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("pid"), F.col("p_size").cast("double").alias("rx"), F.col("p_retailprice").alias("ry"), F.col("p_partkey").cast("double").alias("rz"), F.regexp_extract("p_brand", r"(\d+)$", 1).try_cast("int").alias("brand"))


PARTS_SQL = "SELECT p_partkey AS pid, p_size AS rx, CAST(round(p_retailprice * 100) AS BIGINT) AS ry, p_partkey AS rz, TRY_CAST(regexp_extract(p_brand, '(\\d+)$', 1) AS INTEGER) AS brand FROM part"

CLOUDS = {
    "flat": Cloud(lineitem, Fixed((1, 100, 1)), tuple(RECORD0), LINEITEM_SQL),
    "air": Cloud(lineitem, Span(AIR, (1, 100, 1)), tuple(RECORD0), LINEITEM_SQL),
    "air_s": Cloud(lineitem, Span(AIR, (1, 100, 1)), tuple(RECORD0), LINEITEM_SQL, 4),
    "air_m": Cloud(lineitem, Span(AIR, (1, 100, 1)), tuple(RECORD0), LINEITEM_SQL, 9),
    "air_l": Cloud(lineitem, Span(AIR, (1, 100, 1)), tuple(RECORD0), LINEITEM_SQL, 23),
    "cube": Cloud(lineitem, Span((10**9,) * 3, (1, 100, 1)), tuple(RECORD0), LINEITEM_SQL),
    "grid": Cloud(grid, Fixed((1, 100, 100)), ("return_number",), GRID_SQL),
    "orders": Cloud(orders, Fixed((1, 100, 1)), (), ORDERS_SQL),
    "orders_span": Cloud(orders, Span((10**9,) * 3, (1, 100, 1)), (), ORDERS_SQL),
    "events": Cloud(events, Fixed((1, 1, 100)), ("event_code", "prop"), EVENTS_SQL),
    "embeddings": Cloud(embeddings, Fixed((10**6,) * 3), ("label",), EMBEDDINGS_SQL),
    "documents": Cloud(documents, Fixed(), ("quality", "toxic", "lang_code", "source_code"), DOCUMENTS_SQL),
    "parts": Cloud(parts, Fixed((1, 100, 1)), ("brand",), PARTS_SQL),
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return CLOUDS[name].load(spark, sf_dir)


def on_grid(spark: SparkSession, sf_dir: str, name: str, whole: Frame) -> DataFrame:
    """The cloud on the grid of ``whole``, the frame of all its tiles."""
    points, tiles = apply(load(spark, sf_dir, name), whole), CLOUDS[name].tiles
    if tiles is None:
        return points
    own = table(spark, sf_dir, "supplier").where(F.col("s_nationkey") < tiles).select(F.col("s_suppkey").cast("int").alias("point_source"))
    return points.join(own, "point_source", "left_semi")


def tiled(spark: SparkSession, sf_dir: str, name: str, whole: Frame) -> DataFrame:
    """All points of a cloud's table on the grid of ``whole``, with ``tile``; points without a tile get one above all."""
    points = apply(load(spark, sf_dir, name), whole)
    if CLOUDS[name].tiles is None:
        return points.withColumn("tile", F.lit(0))
    own = table(spark, sf_dir, "supplier").groupBy(F.col("s_suppkey").cast("int").alias("point_source")).agg(F.min("s_nationkey").cast("int").alias("tile"))
    return points.join(own, "point_source", "left").withColumn("tile", F.coalesce("tile", F.lit((1 << 31) - 1)))


def gridded(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, Frame]:
    """The cloud on its natural grid, and its frame."""
    frame = fit_frame(load(spark, sf_dir, name), CLOUDS[name].policy)
    points = on_grid(spark, sf_dir, name, frame)
    return points, frame if CLOUDS[name].tiles is None else replace(frame, count=points.count())


def grid_sql(name: str, columns: str = "") -> str:
    """Common table expressions ``raw``, ``m`` (minima and extents) and ``c`` (the gridded cloud) for DuckDB."""
    cloud = CLOUDS[name]
    if isinstance(cloud.policy, Span):
        axis = lambda a, t: f"CASE WHEN m.h{a} = m.l{a} THEN 0 ELSE CAST((raw.r{a} - m.l{a}) AS HUGEINT) * {t} // (m.h{a} - m.l{a}) END"
        xyz = ", ".join(f"CAST({axis(a, t)} AS BIGINT) AS {a}" for a, t in zip("xyz", cloud.policy.target, strict=True))
        extent = ", ".join(f"CAST({t} AS BIGINT) AS e{a}" for a, t in zip("xyz", cloud.policy.target, strict=True))
    else:
        xyz = ", ".join(f"CAST(raw.r{a} - m.l{a} AS BIGINT) AS {a}" for a in "xyz")
        extent = ", ".join(f"CAST(max(r{a}) - min(r{a}) AS BIGINT) AS e{a}" for a in "xyz")
    attributes = "".join(f", {a}" for a in cloud.attributes)
    bounds = ", ".join(f"min(r{a}) AS l{a}, max(r{a}) AS h{a}" for a in "xyz")
    kept = "" if cloud.tiles is None else f" WHERE point_source IN (SELECT s_suppkey FROM supplier WHERE s_nationkey < {cloud.tiles})"
    return f"raw AS ({cloud.sql}),\nm AS (SELECT {bounds}, {extent} FROM raw),\nc AS (SELECT pid, {xyz}{attributes}, ex, ey, ez{columns} FROM raw, m{kept})"
