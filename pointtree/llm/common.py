"""Shared pieces: word splitting, rolling hashes, written intermediate tables, connected components."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
import weakref
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of words and their hashes that a Python worker keeps before it starts over, and what an entry takes besides its key.
HASH_BYTES, ENTRY_BYTES = 24 << 20, 180
#: A setting of the session that may be changed at any time.
ARROW_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"
_MASK = (1 << 64) - 1
_BASES = (0x9E3779B97F4A7C13, 0xC2B2AE3D27D4EB4B)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_arrow(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; where it is unset, a temporary one on a local master, and else an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="pointtree-")
        atexit.register(shutil.rmtree, found, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(f"file://{found}")
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def small_arrow(spark: SparkSession) -> None:
    """Whole texts go to Python: unless the session says otherwise, in batches of far fewer rows than Spark's usual 10,000."""
    if spark.conf.get(ARROW_ROWS, "10000") == "10000":
        spark.conf.set(ARROW_ROWS, "500")


def store(df: DataFrame, name: str = "table") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    small_arrow(spark)
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path  # type: ignore[attr-defined]
    return out


def release(*tables: DataFrame) -> None:
    """Delete stored tables that no later plan reads."""
    for t in tables:
        if path := getattr(t, "_stored_at", None):
            sc = t.sparkSession.sparkContext
            at = sc._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)


class Bounded(dict):
    """A cache of a worker that starts over at a number of bytes, and whenever the worker comes to another stage.

    One that is ``quick`` to fill goes with each task: Spark keeps more workers than run at a time.
    """

    def __init__(self, most: int, quick: bool = True):
        self.most, self.held, self.quick = most, 0, quick
        _caches.add(self)

    __hash__ = object.__hash__  # type: ignore[assignment]

    def drop(self) -> None:
        self.clear()
        self.held = 0

    def keep(self, key: bytes | str, value: object, size: int = 0) -> None:
        self.held += ENTRY_BYTES + len(key) + size
        if self.held > self.most:
            self.drop()
        self[key] = value


_caches: weakref.WeakSet[Bounded] = weakref.WeakSet()
_stage: list[int | None] = [None]


def begin() -> None:
    """To be called where a task begins: what the worker has cached for other stages goes."""
    context = TaskContext.get()
    stage = context.stageId() if context else None
    if stage != _stage[0]:
        _stage[0] = stage
        for cache in list(_caches):
            cache.drop()
        give_back()


def end() -> None:
    """To be called where a task ends: caches that are quick to fill go."""
    for cache in list(_caches):
        if cache.quick:
            cache.drop()
    give_back()


def give_back() -> None:
    """What allocators hold unused goes back to the system: a worker lives on through many stages."""
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it


class WordHashes(Bounded):
    """bytes -> 64-bit hash, each word hashed once."""

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(word)
        self.keep(word, h)
        return h


_hashes = WordHashes(HASH_BYTES)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    got = _powers.get(which)
    if got is None or len(got[0]) < n:
        size = max(4096, 1 << (n - 1).bit_length())
        base = np.uint64(_BASES[which])
        inverse = np.uint64(pow(_BASES[which], -1, 1 << 64))
        got = tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, b, np.uint64)])) for b in (base, inverse))
        _powers[which] = got
    return got


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def rolling(h: np.ndarray, k: int, which: int = 0) -> np.ndarray:
    """Hash of every run of k consecutive values; equal runs get equal hashes anywhere."""
    n = len(h)
    if n < k:
        return np.empty(0, np.uint64)
    p, inv = _power_tables(which, n + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * p[:n])])
    return mix((sums[k:] - sums[:-k]) * inv[: n - k + 1])


def stretches(h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each run h[start:end], never 0; equal runs get equal hashes anywhere."""
    p, inv = _power_tables(0, len(h) + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * p[: len(h)])])
    return mix((sums[ends] - sums[starts]) * inv[starts] + mix((ends - starts).astype(np.uint64))) | np.uint64(1)


def sliding_min(v: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every w consecutive values, by doubling."""
    done, out = 1, v
    while done * 2 <= w:
        out = np.minimum(out[:-done], out[done:])
        done *= 2
    if done < w:
        step = w - done
        out = np.minimum(out[:-step], out[step:])
    return out


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def lists(values: list[np.ndarray], kind: pa.DataType) -> pa.Array:
    """An Arrow list column of numpy arrays, without Python objects for the values."""
    ends = np.cumsum([0, *map(len, values)]).astype(np.int32)
    flat = np.concatenate(values) if values else np.empty(0)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat, kind))


def text_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes | None]:
    """Texts as UTF-8 bytes."""
    return column.cast(pa.binary()).to_pylist()


def small_batches(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def by_batch(fn: Callable[[pa.RecordBatch], pa.RecordBatch], rows: int = 512) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begin()
        for b in small_batches(batches, rows):
            yield fn(b)
        end()

    return run


def components(edges: DataFrame, most_rounds: int = 100) -> DataFrame:
    """Connected components of ``edges(a, b)``: ``(id, component)`` with the smallest id, for every id in an edge.

    Alternates two star contractions, as many rounds as it takes (some, then one for each doubling of the longest path;
    ``most_rounds`` without an end are an error): each node links its larger neighbours to the smallest of its
    neighbourhood, then each node links its smaller neighbours likewise. Counts decide when the edges stop to change.
    Only minima per node are joined back, and those are written before, so that a hot centre's rows can be split.
    """
    e = store(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    before = None
    for _ in range(most_rounds):
        both = e.union(e.select("b", "a")).toDF("u", "v")
        low = store(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "low")
        # large star: larger neighbours of u go to the smallest of u and its neighbours
        big = store(both.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct(), "big")
        # small star: u's smaller neighbours and u go to the smallest of them
        low2 = store(big.groupBy("a").agg(F.min("b").alias("m")), "low")
        small = big.join(low2, "a")
        new = store(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low2.select("a", F.col("m").alias("b"))).distinct(), "edges")
        mark = new.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        release(e, low, big, low2)
        e = new
        if mark == before:
            break
        before = mark
    else:
        raise RuntimeError(f"components did not come to an end in {most_rounds} rounds")
    return e.select(F.col("a").alias("id"), F.col("b").alias("component")).union(e.select(F.col("b"), F.col("b")).distinct())
