"""Points as a stream: windows, late data, repeats, growing boxes, and delta shards beside a base store."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..config import TreeConfig
from ..functions.quantize import Frame, apply
from ..operators import query
from ..sources import clouds, store
from ..sources.shared import shared_dir

START = "timestamp_ntz'2024-01-01'"


def zoned(events: DataFrame) -> DataFrame:
    return events.withColumn("zone", F.call_function("div", F.col("user_id"), F.lit(10)))


def tumbling(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """Events per zone and window: ``zone, at, n``, with the window's start in seconds. The same plan runs on streams."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    g = events.groupBy("zone", w.alias("w")).agg(F.count("*").alias("n"))
    return g.select("zone", F.expr(f"timestampdiff(SECOND, {START}, w.start)").alias("at"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n")).select("user_id", "n")


def stream_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as a file stream in order of time, a file a batch."""
    t = clouds.table(spark, sf_dir, "events")
    return spark.readStream.schema(t.schema).option("maxFilesPerTrigger", 1).parquet(in_order(t))


def in_order(events: DataFrame, files: int = 4) -> str:
    """Events written one range of time after another, so that a stream takes them in that order."""
    path = f"{shared_dir(events.sparkSession)}/events-{uuid.uuid4().hex}"
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    cuts = events.select(F.percentile_approx(at, [k / files for k in range(1, files)], 1000)).first()[0] or []
    edges = [None, *cuts, None]
    for low, high in zip(edges, edges[1:]):
        part = events.where((at > low if low is not None else F.lit(True)) & (at <= high if high is not None else F.lit(True)))
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def drain(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what there is; each batch is a folder of Parquet files, which a batch that comes again replaces."""
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/drained-{uuid.uuid4().hex}"
    last: list[int] = []

    def keep(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/batch={batch}")
        last.append(batch)

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    if not q.awaitTermination(600):
        q.stop()
        raise TimeoutError("the stream did not end")
    if not last:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*([f"{path}/out/batch={max(last)}"] if mode == "complete" else [f"{path}/out/batch={i}" for i in sorted(set(last))]))


def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream beside a table that does not move."""
    c = clouds.table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    s = stream_of(spark, sf_dir).join(c, F.col("c_custkey") == F.col("user_id"))
    return drain(s.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def stream_late(spark: SparkSession, sf_dir: str, late: bool = True) -> DataFrame:
    """Windows that the watermark has closed, with their counts; events of the first day come again behind all others, and are dropped."""
    t = clouds.table(spark, sf_dir, "events")
    path = in_order(t)
    if late:
        first = t.agg(F.min("ts").alias("t0"))
        again = t.join(F.broadcast(first), F.col("ts") < F.expr("t0 + interval 1 day")).drop("t0")  # one row beside the table
        again.coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(t.schema).option("maxFilesPerTrigger", 1).parquet(path)
    s = zoned(stream).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    closed = s.groupBy("zone", F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drain(closed.select("zone", F.unix_seconds("w.start").alias("at"), "n"), "append").select("zone", "n")


def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event once, though the stream holds every one of them twice."""
    s = stream_of(spark, sf_dir)
    s = s.unionByName(s).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "60 days")
    once = drain(s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append")
    return once.agg(F.count("*").alias("n"))


def stream_split(spark: SparkSession, sf_dir: str, limit: int = 100) -> DataFrame:
    """Points per zone so far, and whether the zone has to be divided: the stop rule of the tree, online."""
    schema = "zone long, n long, divide boolean"

    def grow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"zone": [key[0]], "n": [n], "divide": [n > limit]})

    s = zoned(stream_of(spark, sf_dir)).select("zone", "event_id")
    out = drain(s.groupBy("zone").applyInPandasWithState(grow, schema, "n long", "update", GroupStateTimeout.NoTimeout), "update")
    return out.groupBy("zone").agg(F.max("n").alias("n")).select("zone", "n", (F.col("n") > limit).alias("divide"))


class Ingest:
    """A base store and delta stores; queries run over all of them, compaction makes them one.

    What there is stands in a manifest beside the stores: a row for each delta, by batch, and one for each compaction.
    An ingest that is opened again under the same path goes on with them; a batch that comes again replaces itself, and
    is left out if a compaction has taken it in.
    """

    MANIFEST = "seq long, batch long, upto long, path string"

    def __init__(self, spark: SparkSession, frame: Frame, config: TreeConfig, attributes: tuple[str, ...], path: str | None = None):
        self.spark, self.frame, self.config, self.attributes = spark, frame, config, attributes
        self.path = path or f"{shared_dir(spark)}/ingest-{uuid.uuid4().hex}"
        self.spark.createDataFrame([], self.MANIFEST).write.mode("append").parquet(f"{self.path}/manifest")

    def _note(self, batch: int, upto: int, path: str) -> None:
        self.spark.createDataFrame([(time.time_ns(), batch, upto, path)], self.MANIFEST).coalesce(1).write.mode("append").parquet(f"{self.path}/manifest")

    def _rows(self) -> tuple[list, dict[int, str]]:
        """The last compaction, if any, and the deltas that it has not taken in, by batch; a row a batch."""
        rows = sorted(self.spark.read.schema(self.MANIFEST).parquet(f"{self.path}/manifest").collect(), key=lambda r: r["seq"])
        base = [r for r in rows if r["batch"] < 0][-1:]
        upto = base[0]["upto"] if base else -1
        return base, {r["batch"]: r["path"] for r in rows if r["batch"] > upto}

    @property
    def stores(self) -> list[store.Store]:
        base, deltas = self._rows()
        return [store.open_store(self.spark, p) for p in [*[r["path"] for r in base], *[deltas[k] for k in sorted(deltas)]]]

    def add(self, points: DataFrame, batch: int) -> None:
        """A micro-batch of gridded points as a delta store; it counts once it is in the manifest."""
        base, _ = self._rows()
        if (base and batch <= base[0]["upto"]) or points.isEmpty():
            return
        made = store.build(points, self.frame, self.config, self.attributes, f"{self.path}/delta-{batch}-{uuid.uuid4().hex}")
        self._note(batch, -1, made.path)

    def run(self, stream: DataFrame) -> None:
        q = stream.writeStream.foreachBatch(lambda df, i: self.add(apply(df, self.frame), i)).option("checkpointLocation", f"{self.path}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination(600)

    def _points(self, parts: list[DataFrame]) -> DataFrame:
        if not parts:
            return self.spark.createDataFrame([], "x long, y long, z long" + "".join(f", {a} int" for a in self.attributes))
        return reduce(DataFrame.unionByName, parts)

    def points_in_box(self, box: tuple[int, ...], columns: tuple[str, ...] = ()) -> DataFrame:
        return self._points([query.points_in_box(s, box, columns) for s in self.stores]).select("x", "y", "z", *columns)

    def compact(self) -> store.Store:
        """All stores as one, an empty one if there is none; positions number the points anew."""
        base, deltas = self._rows()
        all_ = self._points([query.scan_all(s) for s in self.stores])
        numbered = all_.withColumn("pid", F.xxhash64(*all_.columns))
        one = store.build(numbered, self.frame, self.config, self.attributes, f"{self.path}/base-{uuid.uuid4().hex}")
        self._note(-1, max([*deltas, base[0]["upto"] if base else -1]), one.path)
        return one


def stream_ingest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events taken in by batches, compacted, and asked for a box."""
    cloud = clouds.CLOUDS["events"]
    _, frame = clouds.gridded(spark, sf_dir, "events")
    t = clouds.load(spark, sf_dir, "events")
    path = f"{shared_dir(spark)}/points-{uuid.uuid4().hex}"
    t.repartitionByRange(3, "rx").write.parquet(path)
    stream = spark.readStream.schema(t.schema).option("maxFilesPerTrigger", 1).parquet(path)
    i = Ingest(spark, frame, TreeConfig(shard_points=5000), cloud.attributes)
    i.run(stream)
    i.compact()
    e = frame.extent
    return i.points_in_box((500_000, 0, 0, 1_500_000, e[1], e[2]), ("event_code",))


