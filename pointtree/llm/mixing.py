"""Mixing sources to target weights: exact block quotas split over output shards by a tree of hypergeometric draws.

A source's documents are dealt to blocks by a hash, which is also their permuted order. The source's target is
a number of whole passes over it plus a rest, and the rest ends inside one block, at the document where the words
come nearest to it; so what a source gives is told by three numbers, and no sort of a source is needed. The drawn
blocks go to output shards: the root of a binary tree holds each source's number of drawn blocks, a node splits its
quotas among its halves by one multivariate hypergeometric draw that its seed fixes, and a block descends to its
shard by its rank. Shards get disjoint runs of permuted blocks; inside a shard draws are shuffled by a hash of the row and
of the pass, so that the copies of a row that is drawn twice don't stand together.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import store, table

BLOCK_BITS = 12
BLOCKS = 1 << BLOCK_BITS
WEIGHTS = (1, 2, 3)
MOST_PASSES = 3
#: Words that an output shard holds on average.
SHARD_WORDS = 2_000_000
#: Sources at most: weights are given for each, and the driver and every task hold a row of each.
MOST_SOURCES = 10_000
WORD = r"[^\x20\x09-\x0D]+"


def targets(sizes: dict[str | None, int], weights: tuple[float, ...] = WEIGHTS, most: int = MOST_PASSES) -> dict[str | None, float]:
    """Each source's share of all words by weight, stopped at ``most`` times its size, the excess shared again."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    left, total, out = set(order), float(sum(sizes.values())), {}
    while left:
        share = sum(weight[s] for s in left)
        got = {s: total * weight[s] / share for s in left}
        over = [s for s in left if got[s] > most * sizes[s]]
        if not over:
            return out | got
        for s in over:
            out[s] = float(most * sizes[s])
            total -= out[s]
            left.discard(s)
    return out


class SplittingTree:
    """Deals ranks 0..quota[s]-1 of each source s to ``shards`` shards."""

    def __init__(self, quotas: list[int], shards: int, seed: int):
        self.quotas, self.shards, self.seed = np.array(quotas, np.int64), max(1, shards), seed
        self.left: dict[tuple[int, int], np.ndarray] = {}

    def _split(self, low: int, high: int, quotas: np.ndarray) -> np.ndarray:
        if (got := self.left.get((low, high))) is None:
            rng = np.random.default_rng([self.seed, low, high])
            total, middle = int(quotas.sum()), (low + high) // 2
            take = total * (middle - low) // (high - low)
            got, rest = np.zeros_like(quotas), total
            for s, n in enumerate(quotas.tolist()):  # one marginal after another
                got[s] = k = min(take, rng.hypergeometric(n, rest - n, take)) if n and take else 0
                take, rest = take - k, rest - n
            self.left[(low, high)] = got
        return got

    def shard(self, source: int, rank: int) -> int:
        low, high, quotas = 0, self.shards, self.quotas
        while high - low > 1:
            left = self._split(low, high, quotas)
            middle = (low + high) // 2
            if rank < left[source]:
                high, quotas = middle, left
            else:
                low, rank, quotas = middle, rank - int(left[source]), quotas - left
        return low


@lru_cache(maxsize=1)
def _tree(quotas: tuple[int, ...], shards: int, seed: int) -> SplittingTree:
    """The worker's tree: nodes that are drawn once stay drawn."""
    return SplittingTree(list(quotas), shards, seed)


def draws(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, seed: int = 1, shard_words: int = SHARD_WORDS) -> DataFrame:
    """``docs`` with columns ``mix_size, mix_source_size, mix_target, mix_hash`` and ``mix_shards``, an entry for each time a row is drawn.

    Needs doc_id, text and source. Null texts have size 0 and a null source is a source of its own, ordered last.
    Rows equal in doc_id and text share a hash and are drawn alike. An empty table gives no rows. More than
    ``MOST_SOURCES`` sources are an error.
    """
    spark = docs.sparkSession
    h = F.xxhash64("doc_id", "text", F.lit(seed))
    sized = docs.withColumns({"mix_size": F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long"), "mix_hash": h, "mix_block": F.shiftrightunsigned(h, 64 - BLOCK_BITS).cast("int")})
    small = store(sized.select("source", "mix_size", "mix_hash", "mix_block"), "sizes")
    blocks = store(small.groupBy("source", "mix_block").agg(F.sum("mix_size").alias("words")), "blocks")
    # one row per source on the driver: weights are given per source, so their number is that of a configuration
    sizes = {r["source"]: r["w"] for r in blocks.groupBy("source").agg(F.sum("words").alias("w")).limit(MOST_SOURCES + 1).collect()}
    if len(sizes) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    goals = targets(sizes, weights)
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    whole = {s: min(MOST_PASSES, int(goals[s] // sizes[s])) if sizes[s] else 0 for s in order}
    rest = {s: goals[s] - whole[s] * sizes[s] for s in order}
    per = spark.createDataFrame([(s, i, float(rest[s])) for i, s in enumerate(order)], "src string, src_no int, rest double")
    by_block = Window.partitionBy("source").orderBy("mix_block")
    cum = blocks.withColumn("cum", F.sum("words").over(by_block)).join(F.broadcast(per), F.col("source").eqNullSafe(F.col("src")))
    cut = [r for r in cum.where("cum - words < rest and cum >= rest and rest > 0").select("src", "mix_block", (F.col("rest") - F.col("cum") + F.col("words")).alias("room")).collect()]
    cuts = {r["src"]: (r["mix_block"], r["room"]) for r in cut}
    edge = spark.createDataFrame([(s, b, room) for s, (b, room) in cuts.items()], "src string, block int, room double")
    in_order = Window.partitionBy("src").orderBy("mix_hash")
    at_edge = small.join(F.broadcast(edge), F.col("source").eqNullSafe(F.col("src")) & (F.col("mix_block") == F.col("block")))
    # rows that share a hash are drawn together and are one row here, however many copies there are
    at_edge = at_edge.groupBy("src", "mix_hash", "room").agg(F.sum("mix_size").alias("words"))
    last = at_edge.withColumn("cum", F.sum("words").over(in_order)).where("cum - words / 2 <= room").groupBy("src").agg(F.max("mix_hash").alias("h")).collect()
    lasts = {r["src"]: r["h"] for r in last}
    rows, quotas = [], []
    for i, s in enumerate(order):
        block = cuts[s][0] if s in cuts else -1 if rest[s] <= 0 else BLOCKS
        rows.append((s, i, whole[s], int(sizes[s]), float(goals[s]), block, lasts.get(s)))
        quotas.append(whole[s] * BLOCKS + min(BLOCKS, block + 1))
    terms = F.broadcast(spark.createDataFrame(rows, "mix_src string, mix_no int, mix_whole int, mix_source_size long, mix_target double, mix_cut int, mix_last long"))
    shards = max(1, math.ceil(sum(goals.values()) / shard_words))
    tree = spark.sparkContext.broadcast((tuple(quotas), shards, seed))

    @F.pandas_udf("array<int>")
    def deal(no: pd.Series, copies: pd.Series, block: pd.Series) -> pd.Series:
        held = _tree(*tree.value)
        return pd.Series([[held.shard(s, p * BLOCKS + b) for p in range(c)] for s, c, b in zip(no, copies, block, strict=True)])

    more = F.when((F.col("mix_block") < F.col("mix_cut")) | ((F.col("mix_block") == F.col("mix_cut")) & (F.col("mix_hash") <= F.col("mix_last"))), 1).otherwise(0)
    out = sized.join(terms, F.col("source").eqNullSafe(F.col("mix_src"))).withColumn("mix_shards", deal("mix_no", F.col("mix_whole") + more, "mix_block"))
    return out.drop("mix_src", "mix_no", "mix_whole", "mix_cut", "mix_last", "mix_block")


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, seed: int = 1) -> DataFrame:
    """The mixture: rows of ``docs`` as often as they are drawn, whole shards one after another in a partition, shuffled inside; the columns of ``docs``.

    Null and empty texts, ties, repeated rows and empty tables are as in ``draws``; names of other columns are free.
    """
    whole = docs.select("doc_id", "text", "source", F.struct(*docs.columns).alias("mix_doc"))
    drawn = draws(whole, weights, seed).select("mix_doc", "mix_hash", F.posexplode("mix_shards").alias("mix_pass", "mix_shard"))
    return drawn.repartition("mix_shard").sortWithinPartitions("mix_shard", F.xxhash64("mix_hash", "mix_pass", F.lit(seed)), "mix_pass").select("mix_doc.*")


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = draws(table(spark, sf_dir, "documents"))
    return d.select("doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("mix_size") * F.size("mix_shards")).alias("taken"), F.col("mix_shards").alias("shards"))
