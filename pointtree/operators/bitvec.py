"""Bit vectors as tables: blocks of 32,768 bits with the ones before each, rank and select by joins."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.quantize import div

#: Bits of a block (what Spark's bitmap aggregate makes), and blocks of a group that one task sums.
BITS, GROUP = 32_768, 4096


def bit_blocks(flags: DataFrame) -> DataFrame:
    """``flags(i, bit)`` as ``block, words, ones, ones_before``. Sums go by groups of blocks, then inside each group."""
    on = flags.select(div(F.col("i"), F.lit(BITS)).alias("block"), F.when(F.col("bit") == 1, F.bitmap_bit_position(F.col("i") + 1)).alias("p"))
    blocks = on.groupBy("block").agg(F.bitmap_construct_agg("p").alias("words")).withColumn("ones", F.bitmap_count("words")).withColumn("grp", div(F.col("block"), F.lit(GROUP)))
    sums = blocks.groupBy("grp").agg(F.sum("ones").alias("n"))
    before = sums.select("grp", F.coalesce(F.sum("n").over(Window.orderBy("grp").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("grp_before"))  # a row for 134 million bits
    inside = F.coalesce(F.sum("ones").over(Window.partitionBy("grp").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return blocks.join(before, "grp").withColumn("ones_before", F.col("grp_before") + inside).select("block", "words", "ones", "ones_before")


def bit_and_rank(rows: DataFrame, blocks: DataFrame, at: str) -> DataFrame:
    """``rows`` with ``bit`` at position ``at`` and ``rank``, the ones in [0, at]; both null where there is no such bit."""
    left = (F.col(at) % BITS).cast("int")
    whole = F.shiftright(left, 3)
    byte = F.conv(F.hex(F.substring("words", whole + 1, F.lit(1))), 16, 10).cast("int")
    place = left.bitwiseAND(F.lit(7))
    held = byte.bitwiseAND(F.call_function("shiftleft", F.lit(2), place) - 1)
    rank = F.col("ones_before") + F.bitmap_count(F.substring("words", F.lit(1), whole)) + F.bit_count(held)
    joined = rows.withColumn("block", div(F.col(at), F.lit(BITS))).join(blocks.select("block", "words", "ones_before"), "block", "left")
    return joined.withColumns({"bit": F.when(byte.bitwiseAND(F.call_function("shiftleft", F.lit(1), place)) != 0, 1).when(byte.isNotNull(), 0), "rank": rank}).drop("block", "words", "ones_before")


def select(numbers: DataFrame, blocks: DataFrame, j: str = "j") -> DataFrame:
    """``numbers`` with ``select1``, the position of the one with that number from 0; numbers beyond the last are dropped.

    A block holds a range of numbers and meets as many bins of 32,768 of them as that range does; numbers join by bin,
    and of each block its numbers are looked up together.
    """
    held = blocks.where("ones > 0").withColumn("last", F.col("ones_before") + F.col("ones") - 1)
    held = held.withColumn("bin", F.explode(F.sequence(div(F.col("ones_before"), F.lit(BITS)), div(F.col("last"), F.lit(BITS)))))
    met = numbers.withColumn("bin", div(F.col(j), F.lit(BITS))).join(held.select("bin", "block", "ones_before", "last"), "bin").where(F.col(j).between(F.col("ones_before"), F.col("last")))
    asked = met.groupBy("block").agg(F.collect_set((F.col(j) - F.col("ones_before")).cast("int")).alias("left"))  # 32,768 of a block at most

    @F.arrow_udf("array<int>")
    def places(words: pa.Array, left: pa.Array) -> pa.Array:
        out = []
        for w, k in zip(words.to_pylist(), left.to_pylist(), strict=True):
            on = np.flatnonzero(np.unpackbits(np.frombuffer(w, np.uint8), bitorder="little"))
            out.append(on[np.array(k, np.int64)].astype(np.int32))
        return pa.array(out, pa.list_(pa.int32()))

    found = asked.join(blocks.select("block", "words", "ones_before"), "block").withColumn("at", places("words", "left"))
    found = found.select("block", "ones_before", F.explode(F.arrays_zip("left", "at")).alias("f"))
    return numbers.join(found.select((F.col("ones_before") + F.col("f.left")).alias(j), (F.col("block") * BITS + F.col("f.at")).alias("select1")), j)
