"""Best-fit-decreasing packing of token sequences into windows.

Overlong documents are first cut into full windows; what remains of each document is one piece shorter
than a window. Best fit decreasing sees nothing of a piece but its length, so the packing is computed on
the histogram of lengths: windows with equal contents are one class with a count, and a segment tree over
remaining capacities finds the tightest class that a length still fits. The plan's size is bounded by the
window length, whatever the corpus holds. Each piece then takes its place by its rank among the pieces of
its length, which needs counts per task and length and no sort of the corpus.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import small_batches, store, table
from .encoding import encoder, tokenizer_path

WINDOW = 2048
END_ID = 1
PIECES = "doc_id long, start long, length int, ids_crc32 long, doc_tokens long, task int, rank long"


class CapacityTree:
    """A segment tree over remaining capacities 0..n: the least non-empty capacity of at least a given size."""

    def __init__(self, n: int):
        self.leaves = 1 << n.bit_length()
        self.any = [False] * (2 * self.leaves)

    def mark(self, capacity: int, there: bool) -> None:
        i = capacity + self.leaves
        self.any[i] = there
        while i > 1:
            i //= 2
            self.any[i] = self.any[2 * i] or self.any[2 * i + 1]

    def tightest(self, size: int) -> int | None:
        i = size + self.leaves
        if self.any[i]:
            return size
        while i > 1:
            if i % 2 == 0 and self.any[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i if self.any[2 * i] else 2 * i + 1
                return i - self.leaves
            i //= 2
        return None


@dataclass
class Placement:
    """Pieces of one length with ranks first_rank.. go, ``each`` to a window from ``offset`` on, to windows first_window.."""

    length: int
    first_rank: int
    count: int
    first_window: int
    offset: int
    each: int


def plan(histogram: dict[int, int], window: int = WINDOW) -> tuple[list[Placement], int]:
    """Best fit decreasing of ``{length: pieces}`` with 0 < length <= window; also the number of windows opened."""
    tree = CapacityTree(window)
    classes: dict[int, list[tuple[int, int]]] = {}  # remaining capacity -> runs (first window, windows)
    out, opened = [], 0

    def put(capacity: int, first: int, n: int) -> None:
        if n:
            classes.setdefault(capacity, []).append((first, n))
            tree.mark(capacity, True)

    for length in sorted((k for k, n in histogram.items() if n), reverse=True):
        left, rank = histogram[length], 0
        while left:
            capacity = tree.tightest(length)
            if capacity is None:
                each = window // length
                capacity, first, n = window, opened, -(-left // each)
                opened += n
            else:
                first, n = classes[capacity].pop()
                if not classes[capacity]:
                    tree.mark(capacity, False)
                each = capacity // length
            # the tightest window stays the tightest until the length no longer fits, so windows fill one by one
            full, rest = divmod(min(left, n * each), each)
            offset = window - capacity
            for windows, per in ((full, each), (1 if rest else 0, rest)):
                if windows:
                    out.append(Placement(length, rank, windows * per, first, offset, per))
                    put(capacity - per * length, first, windows)
                    first, n, rank, left = first + windows, n - windows, rank + windows * per, left - windows * per
            put(capacity, first, n)
    return out, opened


def pieces(docs: DataFrame, tokenizer: str, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """``docs(doc_id, text)`` -> one row per piece with its length, checksum and rank among its task's pieces of that length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context = TaskContext.get()
        task = context.partitionId() if context else 0
        ranks = [0] * (window + 1)
        enc = encoder(tokenizer)
        for b in small_batches(batches, 256):
            rows = []
            for doc, ids in zip(b.column(0).to_pylist(), enc.encode([t or "" for t in b.column(1).to_pylist()]), strict=True):
                ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                n, raw = len(ids), memoryview(ids).cast("B")
                for at in range(0, n, window):
                    k = min(window, n - at)
                    rows.append((doc, at, k, zlib.crc32(raw[4 * at : 4 * (at + k)]), n, task, ranks[k]))
                    ranks[k] += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), KINDS, strict=True)], names=NAMES) if rows else empty()

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)


KINDS = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
NAMES = [c.split()[0] for c in PIECES.split(", ")]


def empty() -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([], t) for t in KINDS], names=NAMES)


def pack(docs: DataFrame, tokenizer: str | None = None, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """Pack ``docs(doc_id, text)`` into windows: one row per piece with ``sequence_id`` and ``offset``.

    Null texts are empty and hold the end id alone; a null doc_id stays null and repeated rows are packed as often
    as they occur; an empty table gives no rows. Ties between equal lengths go by task and row, which the result
    of a run fixes. Columns other than doc_id and text are ignored.
    """
    cut = store(pieces(docs, tokenizer or tokenizer_path("byte_bpe_50k.json"), window, end_id), "pieces")
    counts = cut.groupBy("length", "task").agg(F.count("*").alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    placements, _ = plan(histogram, window)
    before = counts.select("length", "task", (F.sum("n").over(Window.partitionBy("length").orderBy("task")) - F.col("n")).alias("before"))
    ranked = cut.join(before, ["length", "task"]).withColumn("rank", F.col("rank") + F.col("before"))
    by_length: dict[int, list[Placement]] = {}
    for p in placements:
        by_length.setdefault(p.length, []).append(p)
    table_ = {k: ([p.first_rank for p in v], np.array([(p.first_rank, p.first_window, p.offset, p.each) for p in v])) for k, v in by_length.items()}
    shared = docs.sparkSession.sparkContext.broadcast(table_)  # bounded by the window length, not by the corpus

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plans = shared.value
        for b in batches:
            lengths, rank = b.column(b.schema.get_field_index("length")).to_numpy(), b.column(b.schema.get_field_index("rank")).to_numpy()
            sequence, offset = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for i, (k, r) in enumerate(zip(lengths.tolist(), rank.tolist(), strict=True)):
                firsts, rows = plans[k]
                first, to, at, each = rows[bisect_right(firsts, r) - 1]
                sequence[i], offset[i] = to + (r - first) // each, at + (r - first) % each * k
            yield pa.RecordBatch.from_arrays([*[b.column(b.schema.get_field_index(c)) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")], pa.array(sequence), pa.array(offset)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    return ranked.withColumn("length", F.col("length").cast("long")).mapInArrow(place, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
