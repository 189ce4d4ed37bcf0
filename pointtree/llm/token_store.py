"""Token ids on disk: documents compressed one by one with a shared dictionary, and an index of offsets.

A store has three tables under one folder. ``dictionary``: its bytes and their hash, trained on serialized id
arrays of a bounded sample. ``blocks``: runs of documents in ascending doc_id, each run the concatenation of the
documents' frames. ``index``: per document its block, the byte range of its frame there, the dictionary's hash,
the number of its ids and of all ids before it. A short document is read by its index row and one small block.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import by_batch, shared_dir, small_batches, table
from .encoding import encoder, tokenizer_path

END_ID = 1
#: Documents whose ids train the dictionary, ids of each at most, in stretches spread over it, and how many.
SAMPLE_DOCS, SAMPLE_IDS, STRETCHES = 2000, 8192, 16
#: Bytes of the dictionary, and bytes after which a block is closed.
DICTIONARY_BYTES, BLOCK_BYTES = 64 << 10, 1 << 20
LEVEL = 1


def spread(ids: np.ndarray) -> np.ndarray:
    """All ids of a document, or stretches spread evenly over the whole of it."""
    if len(ids) <= SAMPLE_IDS:
        return ids
    each = SAMPLE_IDS // STRETCHES
    return np.concatenate([ids[at : at + each] for at in np.linspace(0, len(ids) - each, STRETCHES).astype(int)])


def train(docs: DataFrame, tokenizer: str, sample: int = SAMPLE_DOCS) -> bytes:
    """A dictionary from the ids of up to ``sample`` documents with the least hashes of id and text; empty if they give none.

    The sample is chosen by hashes alone, its texts are encoded where they lie, and the driver gets at most
    ``SAMPLE_IDS`` ids of each.
    """
    n = docs.count()
    part = min(1.0, 2 * sample / max(1, n))  # so many hashes are likely to be enough, and a few more
    most = int(part * (1 << 63)) * 2 - (1 << 63) - 1
    keyed = docs.select("text", F.xxhash64("doc_id", "text").alias("h")).where(F.col("h") <= F.lit(most))

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        arrays = [spread(a) for a in encoder(tokenizer).encode([t or "" for t in b.column(1).to_pylist()])]
        return pa.RecordBatch.from_arrays([b.column(0), pa.array([a.astype("<u2" if a.max(initial=0) < 1 << 16 else "<u4").tobytes() for a in arrays], pa.binary())], names=["h", "ids"])

    # equal rows are one document here; the texts are so few that two tasks encode them
    rows = keyed.groupBy("h").agg(F.min("text").alias("text")).coalesce(2).mapInArrow(by_batch(run, 256), "h long, ids binary").orderBy("h").limit(sample).collect()
    arrays = [bytes(r["ids"]) for r in rows if len(r["ids"]) >= 8]
    try:
        return zstandard.train_dictionary(min(DICTIONARY_BYTES, max(256, sum(map(len, arrays)) // 4)), arrays, level=LEVEL).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b""  # too few documents to learn from: frames without a dictionary


class Frames:
    """One document's ids <-> a zstandard frame. The first byte tells the width of an id."""

    def __init__(self, dictionary: bytes):
        known = {"dict_data": zstandard.ZstdCompressionDict(dictionary)} if dictionary else {}
        for d in known.values():
            d.precompute_compress(level=LEVEL)  # else it is loaded again for each frame
        self.hash = hashlib.sha256(dictionary).hexdigest()[:16]
        self.packer = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False, **known)
        self.unpacker = zstandard.ZstdDecompressor(**known)

    def pack(self, ids: np.ndarray) -> bytes:
        width = 2 if ids.max(initial=0) < 1 << 16 else 4
        return bytes([width]) + self.packer.compress(ids.astype(f"<u{width}").tobytes())

    def unpack(self, frame: bytes) -> np.ndarray:
        return np.frombuffer(self.unpacker.decompress(frame[1:]), f"<u{frame[0]}").astype("<u4")


BLOCKS = "task int, block int, first_row long, data binary, doc_ids array<long>, sizes array<int>, tokens array<int>"


def write(docs: DataFrame, path: str, tokenizer: str, end_id: int = END_ID) -> None:
    """Encode ``docs(doc_id, text)``, append the end id to each, and write the store under ``path``.

    Null texts are empty; rows with a null doc_id come first; repeated rows are kept, ties in any order. An empty
    table gives a store without documents. Columns other than doc_id and text are ignored.
    """
    spark = docs.sparkSession
    dictionary = train(docs, tokenizer)
    frames_hash = Frames(dictionary).hash
    spark.createDataFrame([(frames_hash, dictionary)], "dictionary_hash string, dictionary binary").coalesce(1).write.parquet(f"{path}/dictionary")
    shared = spark.sparkContext.broadcast(dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, enc, frames = TaskContext.get().partitionId(), encoder(tokenizer), Frames(shared.value)
        block, row = 0, 0
        data, doc_ids, sizes, tokens = [], [], [], []
        held = 0

        def close() -> pa.RecordBatch:
            lists = [pa.array([doc_ids], pa.list_(pa.int64())), pa.array([sizes], pa.list_(pa.int32())), pa.array([tokens], pa.list_(pa.int32()))]
            return pa.RecordBatch.from_arrays([pa.array([task], pa.int32()), pa.array([block], pa.int32()), pa.array([row - len(sizes)], pa.int64()), pa.array([b"".join(data)], pa.binary()), *lists], names=[c.split()[0] for c in BLOCKS.split(", ")])

        for b in small_batches(batches, 256):
            for doc, ids in zip(b.column(0).to_pylist(), enc.encode([t or "" for t in b.column(1).to_pylist()]), strict=True):
                frame = frames.pack(np.append(ids, np.uint32(end_id)))
                data.append(frame)
                doc_ids.append(doc)
                sizes.append(len(frame))
                tokens.append(len(ids) + 1)
                held, row = held + len(frame), row + 1
                if held >= BLOCK_BYTES:
                    yield close()
                    block, held = block + 1, 0
                    data, doc_ids, sizes, tokens = [], [], [], []
        if sizes:
            yield close()

    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    ordered.mapInArrow(run, BLOCKS).write.option("compression", "none").parquet(f"{path}/blocks")
    blocks = spark.read.parquet(f"{path}/blocks").select("task", "block", F.aggregate("tokens", F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))
    # one row per block: first the tasks' sums in order of the ranges, then the blocks of each task
    tasks = blocks.groupBy("task").agg(F.sum("n").alias("n"))
    starts = tasks.select("task", F.coalesce(F.sum("n").over(Window.orderBy("task").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("task_start"))
    within = blocks.select("task", "block", F.coalesce(F.sum("n").over(Window.partitionBy("task").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("block_start"))
    at = within.join(starts, "task").select("task", "block", (F.col("task_start") + F.col("block_start")).alias("start"))
    # Spark takes binary and array columns for far smaller than they are: without the hint it would broadcast them
    per = spark.read.parquet(f"{path}/blocks").select("task", "block", "doc_ids", "sizes", "tokens").hint("merge").join(at, ["task", "block"])

    def offsets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                sizes, tokens = np.array(r["sizes"], np.int64), np.array(r["tokens"], np.int64)
                n = len(sizes)
                yield pa.RecordBatch.from_arrays([pa.array([r["task"]] * n, pa.int32()), pa.array([r["block"]] * n, pa.int32()), pa.array(r["doc_ids"], pa.int64()), pa.array(np.cumsum(sizes) - sizes), pa.array(sizes), pa.array(r["start"] + np.cumsum(tokens) - tokens), pa.array(tokens), pa.array([frames_hash] * n)], names=["task", "block", "doc_id", "at", "size", "start", "n_tokens", "dictionary_hash"])

    per.mapInArrow(offsets, "task int, block int, doc_id long, at long, size long, start long, n_tokens long, dictionary_hash string").write.parquet(f"{path}/index")


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """Documents of a store: ``doc_id, start, n_tokens, ids_crc32`` and, if asked for, ``ids``.

    Frames are checked against the dictionary's hash and the index; rows come as they were written, null ids and
    repeated ones included, and a store without documents gives no rows.
    """
    found = spark.read.parquet(f"{path}/dictionary").first()
    frames_hash, shared = found["dictionary_hash"], spark.sparkContext.broadcast(bytes(found["dictionary"]))
    index = spark.read.parquet(f"{path}/index").groupBy("task", "block").agg(F.sort_array(F.collect_list(F.struct("at", "size", "doc_id", "start", "n_tokens", "dictionary_hash"))).alias("docs"))
    blocks = spark.read.parquet(f"{path}/blocks").select("task", "block", "data").hint("merge").join(index, ["task", "block"])
    names = ["doc_id", "start", "n_tokens", "ids_crc32", *["ids"] * with_ids]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        frames = Frames(shared.value)
        for b in batches:
            for k in range(b.num_rows):
                data, docs, rows = memoryview(b.column("data")[k].as_buffer()), b.column("docs")[k].as_py(), []
                for d in docs:
                    if d["dictionary_hash"] != frames_hash:
                        raise ValueError(f"document {d['doc_id']} was written with dictionary {d['dictionary_hash']}, not {frames_hash}")
                    ids = frames.unpack(bytes(data[d["at"] : d["at"] + d["size"]]))
                    if len(ids) != d["n_tokens"]:
                        raise ValueError(f"document {d['doc_id']} has {len(ids)} ids, its index says {d['n_tokens']}")
                    rows.append((d["doc_id"], d["start"], len(ids), zlib.crc32(ids.tobytes()), *[ids.tolist()] * with_ids))
                kinds = [pa.int64()] * 4 + [pa.list_(pa.int64())] * with_ids
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds, strict=True)], names=names)

    return blocks.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids)


def fetch(spark: SparkSession, path: str, doc_id: int) -> np.ndarray | None:
    """The ids of one document by its index row and its block alone."""
    row = spark.read.parquet(f"{path}/index").where(F.col("doc_id") == doc_id).first()
    if row is None:
        return None
    block = spark.read.parquet(f"{path}/blocks").where((F.col("task") == row["task"]) & (F.col("block") == row["block"])).select(F.substring("data", F.lit(row["at"] + 1), F.lit(row["size"])).alias("f")).first()
    return Frames(bytes(spark.read.parquet(f"{path}/dictionary").first()["dictionary"])).unpack(bytes(block["f"]))


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/token-store-{uuid.uuid4().hex}"
    write(table(spark, sf_dir, "documents"), path, tokenizer_path("word_bpe_49k.json"))
    return read(spark, path)
