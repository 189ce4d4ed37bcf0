"""From raw documents to packed training sequences, stage by stage.

Each stage takes ``(spark, docs, sf_dir)`` and works on all rows its predecessor kept; ``run`` writes what a stage
returns as Parquet in the shared folder and reads it again as the next one's input. Every stage takes an empty table
and gives one; all but the last keep the columns of ``docs``, whatever else they are called, and whole texts of any length.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pointtree.llm import jaccard_join, mixing, packing, substring_dedup, toxicity
from pointtree.llm.common import store, table


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go.

    Null and empty texts have no words and are scored as such; equal texts, and so repeated rows, share their verdict.
    Null ids and labels teach nothing. A score of exactly the threshold is rejected.
    """
    return toxicity.clean(docs, table(spark, sf_dir, "labels"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays, that with the least doc_id; ties go by a hash of the text.

    Rows without words (null, empty, blank) and rows with a null doc_id are no duplicates and stay as often as they
    occur. Rows that share a doc_id but not the text are documents of their own; rows equal in both are copies.
    """
    return jaccard_join.firsts(docs)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words of passages that a document with a smaller doc_id holds are cut from the texts; rows left without words by that go.

    Null and empty texts stay as they are, as do rows with a null doc_id. Rows that share a doc_id don't cut each other.
    """
    return substring_dedup.deduped(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mixture of their sources takes them, up to three times, shuffled within output shards.

    A null source is one of its own, ordered last; null and empty texts have size 0 and go with their block. Rows equal in doc_id
    and text are drawn alike. A document that is drawn twice is two rows.
    """
    return mixing.mix(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the token sequences with their places in windows.

    Null and empty texts hold the end id alone; a null doc_id stays null; repeated rows are packed as often as they occur.
    """
    return packing.pack(docs)


STAGES = [
    ("toxicity", reject_toxic),
    ("ngram_jaccard_join", drop_near_duplicates),
    ("substring_dedup", cut_repeated_passages),
    ("mix_sources", mix_sources),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = store(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)


#: No stage but the third is expressible in SQL; brute-force versions of the stages are in tests/llm.
ORACLE_SQL = None
