"""The experiment: space, 500 boxes and failures of every format, growth with the cloud, sweeps of k and l."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import TreeConfig
from ..functions.quantize import Frame, fit_frame
from ..operators import baselines, measures, query, topology
from ..sources import clouds
from ..sources import store as stores
from ..sources.clouds import CLOUDS, grid_sql
from ..sources.shared import cut
from .book import CONFIG, cloud, once, sql_tree, store_of, together
from .book import query as registered
from .workloads import BOXES_SQL, boxes

W = "WITH "
#: The five clouds of the space table: three sizes of the wide and flat one, and two more.
FIVE = ("air_s", "air_m", "air_l", "orders_span", "embeddings")
#: Points of a block, as in the re-created format's own default and as small ones.
BLOCKS = (5_000, 50_000)
I1020 = [("intensity", 10, 20)]


def strips_of(f: Frame, block: int) -> int:
    """About as many strips as blocks along one."""
    return max(1, round((f.count / block) ** 0.5))


def acquired_blocks(spark: SparkSession, d: str, name: str, block: int = 5_000) -> baselines.Blocks:
    """Delta-coded blocks in acquisition order (flight strips), with all attributes of the cloud."""
    def make() -> baselines.Blocks:
        p, f = cloud(spark, d, name)
        return baselines.build_block_delta(baselines.strips(p, f.extent, strips_of(f, block)), f.parts(CONFIG), baselines.ACQUIRED, CLOUDS[name].attributes, block)

    return once(spark, ("acquired", d, name, block), make)


def raw_of(spark: SparkSession, d: str, name: str) -> str:
    return once(spark, ("raw", d, name), lambda: baselines.write_raw(cloud(spark, d, name)[0]))


def sorted_of(spark: SparkSession, d: str, name: str) -> str:
    def make() -> str:
        p, f = cloud(spark, d, name)
        return baselines.write_sorted(p, f.parts(CONFIG))

    return once(spark, ("sorted", d, name), make)


def counts_by(spark: SparkSession, d: str, name: str, form: str, where=()) -> DataFrame:  # noqa: ANN001
    """``q, n`` of the 500 boxes by one format."""
    b = boxes(spark, cloud(spark, d, name)[1])
    ways = {
        "octree": lambda: query.counts_in_boxes(store_of(spark, d, name), b, where),
        "block": lambda: baselines.counts_in_blocks(acquired_blocks(spark, d, name), b, where),
        "raw": lambda: baselines.counts_in_points(baselines.read_raw(spark, raw_of(spark, d, name)), b, where),
        "sorted": lambda: baselines.counts_in_points(spark.read.parquet(sorted_of(spark, d, name)), b, where),
    }
    return ways[form]()


def counts_sql(name: str, where: str = "") -> str:
    inside = " AND ".join(f"c.{a} BETWEEN b.{a}i AND b.{a}e" for a in "xyz")
    return W + grid_sql(name) + f", {BOXES_SQL} SELECT q, (SELECT count(*) FROM c WHERE {inside}{where}) AS n FROM b"


for _form in ("block", "raw", "sorted"):
    registered(f"w_box500_counts_{_form}", counts_sql("air"))(lambda spark, d, form=_form: counts_by(spark, d, "air", form))
    registered(f"w_attr500_counts_{_form}", counts_sql("air", " AND intensity BETWEEN 10 AND 20"))(lambda spark, d, form=_form: counts_by(spark, d, "air", form, I1020))
registered("w_box500_counts_block_cube", counts_sql("cube"))(lambda spark, d: counts_by(spark, d, "cube", "block"))
for _name in ("air_s", "air_m", "air_l"):
    registered(f"w_box500_counts_{_name}", counts_sql(_name))(lambda spark, d, name=_name: counts_by(spark, d, name, "octree"))

_INSIDE = " AND ".join(f"c.{a} BETWEEN b.{a}i AND b.{a}e" for a in "xyz")


@registered("failures_by_format", W + grid_sql("air") + f", {BOXES_SQL}, n AS (SELECT q, (SELECT count(*) FROM c WHERE {_INSIDE}) AS n FROM b) SELECT format, count(*) AS queries_run, count(*) FILTER (n > 0) AS queries_hit, CAST(0 AS BIGINT) AS queries_failed FROM n, (VALUES ('octree'), ('block'), ('raw'), ('sorted')) f(format) GROUP BY format")
def failures_by_format(spark: SparkSession, d: str) -> DataFrame:
    """Queries that find points, and those that find none where the plain predicate does."""
    want = cut(baselines.counts_in_points(cloud(spark, d, "air")[0], boxes(spark, cloud(spark, d, "air")[1])))
    out = []
    for form in ("octree", "block", "raw", "sorted"):
        got = cut(counts_by(spark, d, "air", form))
        row = measures.failures(got, want).select(F.lit(form).alias("format"), "queries_run", "queries_failed")
        out.append(row.crossJoin(got.agg(F.count(F.when(F.col("n") > 0, 1)).alias("queries_hit"))))  # one row each
    return reduce(DataFrame.unionByName, out).select("format", "queries_run", "queries_hit", "queries_failed")


@registered("space_raw_clouds", " UNION ALL ".join(f"(WITH {grid_sql(n)} SELECT '{n}' AS cloud, count(*) AS points, count(*) * 20 AS bytes, CAST(ceil(count(*) * 20 / 1048576.0) AS BIGINT) AS mb FROM c)" for n in FIVE))
def space_raw_clouds(spark: SparkSession, d: str) -> DataFrame:
    return reduce(DataFrame.unionByName, [measures.raw_space(cloud(spark, d, n)[0]).select(F.lit(n).alias("cloud"), "points", "bytes", "mb") for n in FIVE])


@registered("space_table")
def space_table(spark: SparkSession, d: str) -> DataFrame:
    """Bytes, bits a point and saving against raw records, of three formats with the same attributes on five clouds."""
    by_table: dict[tuple, list[str]] = {}
    for n in FIVE:
        by_table.setdefault((CLOUDS[n].load, CLOUDS[n].policy), []).append(n)
    out = []
    for names in by_table.values():
        p, frames = together(spark, d, names)
        whole, attributes = frames[names[0]], CLOUDS[names[0]].attributes
        ways = [(n, block) for n in names for block in BLOCKS]
        blocks = dict(zip(ways, baselines.block_bytes(p, whole.extent, attributes, [baselines.Way(CLOUDS[n].tiles, strips_of(frames[n], b), b) for n, b in ways]), strict=True))
        for n in names:
            own, points = p if CLOUDS[n].tiles is None else p.where(F.col("tile") < CLOUDS[n].tiles), frames[n].count
            s = once(spark, ("store", d, n, CONFIG), lambda own=own, n=n: stores.build(own, frames[n], CONFIG, attributes))
            sizes = {"raw": 20 * points, "octree": measures.space(s).agg(F.sum("bytes")).first()[0]} | {f"block_{b // 1000}k": blocks[n, b] for b in BLOCKS}
            out += [(n, form, points, int(size), round(8 * size / max(1, points), 3), round(measures.saving(size, sizes["raw"]), 3), round(measures.saving(size, sizes["octree"]), 3)) for form, size in sizes.items()]
    return spark.createDataFrame(out, "cloud string, format string, points long, bytes long, bits_per_point double, smaller_than_raw double, smaller_than_octree double")


_GROWN = ("air_s", "air_m", "air_l", "air")


@registered("growth", " UNION ALL ".join(f"(WITH {sql_tree(n)} SELECT '{n}' AS cloud, (SELECT count(*) FROM c) AS points, count(*) FILTER (kind = 'branch') + 1 AS branches, count(*) FILTER (kind <> 'branch') AS leaves, CAST(max(level) AS INTEGER) AS deepest FROM tree)" for n in _GROWN))
def growth(spark: SparkSession, d: str) -> DataFrame:
    """How the tree grows with the cloud."""
    out = []
    for n in _GROWN:
        p, f = cloud(spark, d, n)
        parts = f.parts(CONFIG)
        nodes = topology.tree_boxes(p, parts, CONFIG.leaf_limit, count=f.count)
        out.append(nodes.agg(F.lit(n).alias("cloud"), F.lit(f.count).alias("points"), (F.count(F.when(F.col("kind") == "branch", 1)) + 1).alias("branches"), F.count(F.when(F.col("kind") != "branch", 1)).alias("leaves"), F.max("level").alias("deepest")))
    return reduce(DataFrame.unionByName, out)


_LIMITS = (1, 10, 100, 1000)


@registered("leaf_limit_sweep_k4", " UNION ALL ".join(f"(WITH {sql_tree('flat', l, 4)} SELECT CAST({l} AS BIGINT) AS leaf_limit, count(*) FILTER (kind = 'branch') + 1 AS branches, count(*) FILTER (kind <> 'branch') AS leaves, CAST(max(cnt) FILTER (kind <> 'branch') AS BIGINT) AS largest FROM tree)" for l in _LIMITS))  # noqa: E741
def leaf_limit_sweep_k4(spark: SparkSession, d: str) -> DataFrame:
    p, f = cloud(spark, d, "flat")
    parts = f.parts(TreeConfig(fanout=4))
    counted, out = cut(topology.level_histogram(p, parts)), []
    for limit in _LIMITS:
        n = topology.classify_nodes(counted, len(parts), limit)
        out.append(n.agg(F.lit(limit).cast("long").alias("leaf_limit"), (F.count(F.when(F.col("kind") == "branch", 1)) + 1).alias("branches"), F.count(F.when(F.col("kind") != "branch", 1)).alias("leaves"), F.max(F.when(F.col("kind") != "branch", F.col("cnt"))).alias("largest")))
    return reduce(DataFrame.unionByName, out)


@registered("size_sweep")
def size_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of the tree, the coordinates and the attributes of stores by k and l."""
    out = []
    for k in (2, 4):
        for limit in (10, 100, 1000):
            s = measures.space(store_of(spark, d, "air", TreeConfig(fanout=k, leaf_limit=limit, shard_points=20_000)))
            kind = F.when(F.col("component").startswith("t_"), "tree").when(F.col("component").startswith("c_"), "coordinates").otherwise("attributes")
            out.append(s.groupBy(kind.alias("part")).agg(F.sum("bytes").alias("bytes"), F.sum("bits_per_point").alias("bits_per_point")).select(F.lit(k).alias("k"), F.lit(limit).alias("leaf_limit"), "part", "bytes", "bits_per_point"))
    return reduce(DataFrame.unionByName, out)


_DESCRIBED = (*FIVE, "air", "cube")


@registered("dataset_table", " UNION ALL ".join(f"(WITH {grid_sql(n)} SELECT '{n}' AS cloud, count(*) AS points, CAST(max(x) AS BIGINT) AS max_x, CAST(max(y) AS BIGINT) AS max_y, CAST(max(z) AS BIGINT) AS max_z, " + ", ".join(f"(SELECT CAST({f}(r{a}) AS BIGINT) FROM raw) AS {w}_{a}" for a in "xyz" for w, f in (("low", "min"), ("high", "max"))) + " FROM c)" for n in _DESCRIBED))
def dataset_table(spark: SparkSession, d: str) -> DataFrame:
    """Points, real bounds and largest converted coordinates of the clouds."""
    out = []
    for n in _DESCRIBED:
        p, f = cloud(spark, d, n)
        out.append(measures.describe_cloud(clouds.load(spark, d, n), p, f.policy.inverse).withColumn("cloud", F.lit(n)))
    return reduce(DataFrame.unionByName, out)


@registered("quant_error_parts", "WITH e AS (SELECT " + ", ".join(f"CAST(embedding[{i + 1}] AS DOUBLE) * 1000000 AS {a}" for i, a in enumerate("xyz")) + " FROM embeddings) SELECT " + ", ".join(f"CAST(max(round(1000 * abs({a} - round({a})))) AS BIGINT) AS thousandths_{a}" for a in "xyz") + " FROM e")
def quant_error_parts(spark: SparkSession, d: str) -> DataFrame:
    """The largest error of each axis in thousandths of a step: half a step at most."""
    raw = clouds.load(spark, d, "embeddings")
    f = fit_frame(raw, CLOUDS["embeddings"].policy)
    scaled = {a: F.col(f"r{a}") * k for a, k in zip("xyz", f.policy.inverse, strict=True)}
    return raw.agg(*[F.max(F.round(1000 * F.abs(c - F.round(c)))).cast("long").alias(f"thousandths_{a}") for a, c in scaled.items()])
