"""All queries of the point-cloud engine and their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .operators import leaves
from .plans import book, core, experiments, surround
from .plans.workloads import part_box

__all__ = ["core", "entry", "experiments", "oracle_sql", "queries", "surround"]
HALF = ((0, 0, 0), (500, 500, 500))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points of the flagship cloud in half of each axis, from the leaf table."""
    points, frame = book.cloud(spark, sf_dir, "air")
    table = leaves.build(points, book.CONFIG, frame.parts(book.CONFIG), ("intensity",))
    return leaves.points_in_box(table, part_box(frame, *HALF), ("intensity",))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(book.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(book.ORACLES)
