"""Exact near-duplicate groups by Jaccard similarity of word shingles: a metric join over regions and pivots.

Jaccard distance is a metric, but texts that share nothing all lie at distance 1 of each other: Voronoi regions around
pivots that are drawn from the corpus at random would each keep such a text as a boundary document. The first
regions are therefore grown from what two near texts must share. Of each set the few shingles that come first in one
global order are its region keys: two sets within the radius share a key for certain (rare shingles come first, so that
regions stay small), and regions of the same sets are one. From there on a region is joined with pivots:

1. Large regions choose a few pivots, the same ones wherever regions overlap; stars around these are joined first,
   and what links is contracted to one label. Regions of one label are done.
2. Large regions are cut by sizes (distances to the empty set), with windows of the triangle inequality, then
   dealt by blocks; inside a cell Voronoi cells are split recursively (see ``regions``). This works on sketches, whose
   distances never exceed the true ones, and leaves small groups of sets that may link.
3. These groups get their whole sets and are joined exactly, with pivots and the triangle inequality.

Equal sets are one node throughout; their members follow at the end.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import regions as metric
from .common import begin, by_batch, components, end, lists, release, rolling, signed, small_batches, store, table, text_bytes, word_hashes

SHINGLE = 5
#: Similarity in per cent at which two sets link.
PERCENT = 80
#: Counters of the sketch by which frequent shingles come last; its size does not grow with the corpus.
SKETCH_BITS = 17
#: Sets from which on a region is joined with pivots first, how many, and the sets of a star that one task joins.
LARGE, PIVOTS, STAR = 32, 4, 512
#: Sets of a cell; larger regions are dealt to several cells.
CELL = 1024
#: Ids that are broadcast at most (8 bytes each); beyond, they are joined by shuffles.
MOST_IDS = 1_000_000
FOLD = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def shingles(raw: bytes | None, k: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles; of the whole sequence where there are fewer words; none without words."""
    words = (raw or b"").translate(FOLD).split()
    if not words:
        return np.empty(0, np.uint64)
    h = word_hashes(words)
    return np.unique(rolling(h, k) if len(words) >= k else rolling(h, len(words)) ^ np.uint64(len(words)))


def _bucket(s: np.ndarray) -> np.ndarray:
    return (s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)


def _sketch(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begin()
        counts = np.zeros(1 << SKETCH_BITS, np.int64)
        for b in small_batches(batches):
            for t in text_bytes(b.column(0)):
                counts += np.bincount(_bucket(rolling(word_hashes((t or b"").translate(FOLD).split()), k)), minlength=len(counts))
        at = np.flatnonzero(counts)
        end()
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(counts[at])], names=["bucket", "n"])

    return run


def _scan(k: int, percent: int, frequent: np.ndarray):
    """Texts -> size, fingerprint, keys and sketch of the set."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        sizes, prints, keys, sketches = [], [], [], []
        for t in text_bytes(b.column(1)):
            s = shingles(t, k)
            n = len(s)
            sizes.append(n)
            prints.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if n else None)
            least = -(-percent * n // 100)  # the overlap with any set that links
            order = np.argsort(frequent[_bucket(s)], kind="stable")
            keys.append(signed(s[order[: n - least + 1]]) if n else np.empty(0, np.int64))
            sketches.append(metric.parity(s, metric.width(n)) if n else None)
        return pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(sizes, pa.int64()), pa.array(prints, pa.binary()), lists(keys, pa.int64()), pa.array(sketches, pa.binary())], names=["doc_id", "row", "size", "print", "keys", "sketch"])

    return by_batch(run)


def _groups(percent: int):
    """Rows sorted by cell -> the groups of sets of each cell that may link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, nodes = [], []
        for t in metric.runs(batches, "cell"):
            for name, members in metric.clusters(t.column("node").to_numpy(), t.column("size").to_numpy(), t.column("sketch").to_pylist(), t.column("label").to_numpy(), percent):
                names += [name] * len(members)
                nodes.append(members)
            if len(names) > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(np.concatenate(nodes))], names=["grp", "node"])
                names, nodes = [], []
        if names:
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(np.concatenate(nodes))], names=["grp", "node"])

    return run


def _links(percent: int):
    """Rows sorted by group, with whole sets -> links."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in metric.runs(batches, "grp"):
            sets = [np.frombuffer(s, np.uint64) for s in t.column("shingles").to_pylist()]
            found = metric.links(t.column("node").to_numpy(), t.column("label").to_numpy(), sets, percent)
            if found:
                a, b = zip(*found, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return run


def _whole(source: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """``print, shingles`` of the documents of ``wanted(doc_id, print)``."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        sets = [shingles(t, k).tobytes() for t in text_bytes(b.column(0))]
        return pa.RecordBatch.from_arrays([pa.array([hashlib.blake2b(s, digest_size=16).digest() for s in sets], pa.binary()), pa.array(sets, pa.binary())], names=["print", "shingles"])

    ids = store(wanted.select("doc_id").distinct(), "wanted")
    few = ids.count() <= MOST_IDS
    return source.join(F.broadcast(ids) if few else ids.hint("merge"), "doc_id", "left_semi").select("text").mapInArrow(by_batch(run), "print binary, shingles binary")


def _join_cells(cells: DataFrame, heads: DataFrame, sketches: DataFrame, labels: DataFrame | None, source: DataFrame, k: int, percent: int) -> DataFrame:
    """Links ``a, b`` that join what links join within each cell of ``cells(cell, node)``."""
    named = lambda df: df.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")) if labels else df.withColumn("label", F.col("node"))
    rows = named(cells.join(sketches.hint("merge"), "node")).select("cell", "node", "size", "label", "sketch")
    found = rows.repartition("cell").sortWithinPartitions("cell").mapInArrow(_groups(percent), "grp binary, node long")
    groups = store(found.distinct(), "groups")
    members = store(heads.join(groups.select("node").distinct(), "node").select("node", "doc_id", "print"), "members")
    sets = members.select("node", "print").join(_whole(source, members, k).hint("merge"), "print").select("node", "shingles")
    rows = named(groups).join(sets.hint("merge"), "node").select("grp", "node", "label", "shingles")
    out = store(rows.repartition("grp").sortWithinPartitions("grp").mapInArrow(_links(percent), "a long, b long"), "links")
    release(groups, members)
    return out


def _deal(rows: DataFrame) -> DataFrame:
    """``rows(region, node, size, n)`` -> ``cell, node``: small regions are cells; large ones are cut by sizes, then by blocks.

    Sets that link have sizes of one class or of neighbouring classes, so each class is joined with the next one. If
    that is too much for a task still, blocks of it are joined two by two.
    """
    small = rows.where(F.col("n") <= CELL).select(F.xxhash64("region").alias("cell"), "node")
    classes = rows.where(F.col("n") > CELL).withColumn("class", F.floor(F.log("size") / math.log(1.01 * 100 / PERCENT)))
    wide = classes.select("region", "node", F.explode(F.array("class", F.col("class") - 1)).alias("class"))
    counts = wide.groupBy("region", "class").agg(F.count("*").alias("m")).withColumn("blocks", F.ceil(F.col("m") / CELL))
    wide = wide.join(counts.hint("merge"), ["region", "class"]).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other")
    pairs = wide.select("region", "class", "node", "block", other)
    return small.union(pairs.select(F.xxhash64("region", "class", F.least("block", "other"), F.greatest("block", "other")), "node"))


def groups(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """``doc_id, row, n_shingles, component_id, root`` per row of ``docs``; ``row`` is a hash of the text, ``root`` names the group."""
    spark = docs.sparkSession
    source = docs.select("doc_id", "text")
    counts = np.zeros(1 << SKETCH_BITS, np.int64)
    # one count per bucket: the driver gets 2**SKETCH_BITS numbers at most
    for r in source.select("text").mapInArrow(_sketch(k), "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[r["bucket"]] = r["n"]
    usual = float(np.median(counts))
    shared = spark.sparkContext.broadcast(counts > 1.2 * usual + 8 * np.sqrt(usual) + 8)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _scan(k, percent, shared.value)(batches)

    sets = store(source.select("doc_id", "text", F.xxhash64("text").alias("row")).mapInArrow(scan, "doc_id long, row long, size long, print binary, keys array<long>, sketch binary"), "sets")
    slim = store(sets.select("doc_id", "row", "size", "print"), "slim")
    # one node per set: its least doc_id, or a hash where sets that differ share that
    heads = slim.where("size > 0 and doc_id is not null").groupBy("print").agg(F.min("doc_id").alias("doc_id"))
    heads = store(heads, "heads")
    twice = heads.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", F.lit(True).alias("twice"))
    heads = store(heads.join(twice, "doc_id", "left").select("print", "doc_id", F.when(F.col("twice"), F.xxhash64("print")).otherwise(F.col("doc_id")).alias("node")), "nodes")
    # rows equal in doc_id and set are one here
    own = store(sets.join(heads.hint("merge"), ["print", "doc_id"]).select("node", "size", "keys", "sketch"), "own")
    release(sets)
    entries = own.select("node", "size", F.explode("keys").alias("key"))
    shared_keys = entries.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    placed = store(entries.join(shared_keys, "key").distinct(), "placed")
    marks = placed.groupBy("key").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("x"), F.bit_xor(F.xxhash64("node", F.lit(2))).alias("y")).where("n > 1")
    # regions of the same sets are one
    kept = store(marks.groupBy("n", "x", "y").agg(F.min("key").alias("key")).select("key", "n"), "kept")
    regions = store(placed.join(kept, "key").select(F.col("key").alias("region"), "node", "size", "n"), "regions")
    release(placed, kept)
    sketches = store(own.select("node", "size", "sketch").join(regions.select("node").distinct(), "node").dropDuplicates(["node"]), "sketches")
    release(own)

    def joined(cells: DataFrame, labels: DataFrame | None) -> DataFrame:
        return _join_cells(cells, heads, sketches, labels, source, k, percent)

    # hashes of the nodes alone choose pivots, so that regions that overlap choose the same
    large = regions.where(F.col("n") > LARGE)
    drawn = [F.min(F.struct(F.xxhash64("node", F.lit(i)).alias("h"), F.col("node").alias("pivot"), F.col("size").alias("pivot_size"))).alias(f"q{i}") for i in range(PIVOTS)]
    pivots = large.groupBy("region").agg(*drawn).select("region", F.explode(F.array_distinct(F.array(*[F.struct(f"q{i}.pivot", f"q{i}.pivot_size") for i in range(PIVOTS)]))).alias("q")).select("region", "q.*")
    alike = F.least("size", "pivot_size") * 100 >= F.greatest("size", "pivot_size") * percent
    stars = store(large.join(pivots, "region").where(alike & (F.col("node") != F.col("pivot"))).select("pivot", "node").distinct(), "stars")
    spokes = stars.groupBy("pivot").agg(F.ceil(F.count("*") / STAR).alias("parts"))
    dealt = stars.join(spokes.hint("merge"), "pivot").select(F.xxhash64("pivot", F.pmod(F.xxhash64("node"), F.col("parts"))).alias("cell"), "node")
    centres = spokes.select(F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"), "pivot").select(F.xxhash64("pivot", "part"), "pivot")
    first = joined(dealt.union(centres), None)
    labels = store(components(first).select(F.col("id").alias("node"), F.col("component").alias("label")), "labels")
    # regions whose sets have different labels still
    told = store(regions.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")), "told")
    open_ = store(told.groupBy("region").agg(F.min("label").alias("c"), F.max("label").alias("d")).where("c < d").select("region"), "open")
    second = joined(_deal(told.join(open_, "region").select("region", "node", "size", "n")), labels)
    final = store(components(first.union(second)).select(F.col("id").alias("node"), "component"), "final")
    named = heads.join(final, "node", "left").withColumn("root", F.coalesce("component", "node"))
    named = store(named.select("print", "doc_id", "root"), "named")
    least = named.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    found = store(named.drop("doc_id").join(least, "root"), "found")
    release(regions, sketches, stars, first, labels, told, open_, second, final, named, heads)
    out = slim.withColumn("print", F.when(F.col("doc_id").isNotNull(), F.col("print"))).join(found, "print", "left")
    return out.select("doc_id", "row", F.col("size").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"), "root")


def join(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """``doc_id, n_shingles, component_id`` per row of ``docs(doc_id, text)``.

    Null, empty and blank texts have no shingles and link with nothing. Rows with a null doc_id link with nothing and
    have a null component. Repeated rows have equal sets and get equal results; rows that share a doc_id but not the
    text are sets of their own. An empty table gives no rows.
    """
    return groups(docs, k, percent).select("doc_id", "n_shingles", "component_id")


def firsts(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """One row of each group of near duplicates stays, one with its least doc_id; the columns of ``docs``.

    Rows without words or with a null doc_id are no duplicates and stay, however often they occur; an empty table
    gives no rows. Of rows that share the least doc_id of their group, that with the least text hash stays.
    """
    found = groups(docs, k, percent).where("root is not null")
    stay = found.groupBy("root").agg(F.min(F.struct("doc_id", "row")).alias("r")).select("r.*")
    again = found.groupBy("doc_id", "row").agg(F.count("*").alias("n")).where("n > 1")
    whole = docs.select("doc_id", F.xxhash64("text").alias("row"), F.struct(*docs.columns).alias("doc"))
    lone = F.col("doc_id").isNull() | ~F.coalesce(F.col("doc.text").rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    kept = whole.where(~lone).join(stay, ["doc_id", "row"], "left_semi")
    if not again.isEmpty():
        kept = kept.dropDuplicates(["doc_id", "row"])
    return kept.select("doc.*").union(whole.where(lone).select("doc.*"))


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(table(spark, sf_dir, "documents"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents),
g AS (SELECT DISTINCT doc_id, md5(array_to_string(words[i:i + 4], ' ')) AS s FROM (SELECT doc_id, words, unnest(generate_series(1, greatest(1, len(words) - 4))) AS i FROM w WHERE len(words) > 0)),
n AS (SELECT doc_id, count(*) AS size FROM g GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS overlap FROM g a JOIN g b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * overlap >= 80 * (x.size + y.size - overlap)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
r AS (SELECT a AS id, a AS reach FROM e UNION SELECT r.id, e.b FROM r JOIN e ON r.reach = e.a),
c AS (SELECT id, min(reach) AS component FROM r GROUP BY id)
SELECT w.doc_id, CAST(coalesce(n.size, 0) AS BIGINT) AS n_shingles, coalesce(c.component, w.doc_id) AS component_id FROM w LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.id = w.doc_id
"""
