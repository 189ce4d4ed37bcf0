"""Queries of the training-data operators and their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession

from . import embedding_dedup, jaccard_join, substring_dedup, warc
from .embedding_dedup import op2_embedding_dedup
from .html_text import op8_html_text
from .jaccard_join import op4_jaccard_join
from .mixing import op7_mixing
from .packing import op3_packing
from .quality import op10_quality
from .substring_dedup import op1_substring_dedup
from .token_store import op9_token_store
from .toxicity import op6_toxicity
from .warc import op5_warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_substring_dedup, op2_embedding_dedup, op3_packing, op4_jaccard_join, op5_warc, op6_toxicity, op7_mixing, op8_html_text, op9_token_store, op10_quality]
    return {f.__name__: f for f in found} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op1_substring_dedup": substring_dedup.ORACLE, "op2_embedding_dedup": embedding_dedup.ORACLE, "op4_jaccard_join": jaccard_join.ORACLE, "op5_warc": warc.ORACLE}
