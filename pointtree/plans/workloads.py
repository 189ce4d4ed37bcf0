"""Query boxes: 500 of ten sizes from an integer formula that Spark and DuckDB share, and single ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.quantize import Box, Frame, div

#: Sizes per mille of an axis, and multipliers and shifts of the positions per axis.
SIZES = (100, 150, 200, 250, 300, 400, 500, 600, 800, 1000)
PLACES = ((389, 13), (571, 17), (733, 29))
MODULUS = 1009


def boxes(spark: SparkSession, frame: Frame, n: int = 500) -> DataFrame:
    """``q, pm, xi, yi, zi, xe, ye, ze`` in grid coordinates."""
    q = F.col("id")
    b = spark.range(n).select(q.alias("q"), F.element_at(F.array(*map(F.lit, SIZES)), (q % 10 + 1).cast("int")).alias("pm"))
    for a, (m, s), e in zip("xyz", PLACES, frame.extent, strict=True):
        low = div(((F.col("q") * m + s) % MODULUS) * F.lit(e).cast("long"), F.lit(MODULUS))
        b = b.withColumn(f"{a}i", low).withColumn(f"{a}e", F.least(F.col(f"{a}i") + div(F.lit(e).cast("long") * F.col("pm"), F.lit(1000)), F.lit(e).cast("long")))
    return b.select("q", "pm", "xi", "yi", "zi", "xe", "ye", "ze")


BOXES_SQL = "b AS (SELECT q, pm, " + ", ".join(f"{a}i, least({a}i + e{a} * pm // 1000, e{a}) AS {a}e" for a in "xyz") + " FROM (SELECT q, pm, m.ex, m.ey, m.ez, " + ", ".join(f"((q * {m} + {s}) % {MODULUS}) * e{a} // {MODULUS} AS {a}i" for a, (m, s) in zip("xyz", PLACES, strict=True)) + f" FROM (SELECT range AS q, ([{', '.join(map(str, SIZES))}])[CAST(range % 10 AS INTEGER) + 1] AS pm FROM range(500)), m))"


def part_box(frame: Frame, low: tuple[int, int, int], high: tuple[int, int, int]) -> Box:
    """A box between per-mille parts of each axis."""
    return tuple(e * p // 1000 for e, p in zip((*frame.extent, *frame.extent), (*low, *high), strict=True))


THIRD = ((200, 200, 200), (500, 500, 500))
SLAB = ((0, 0, 400), (1000, 1000, 420))
COLUMN = ((330, 330, 0), (360, 360, 1000))
SMALL = ((400, 400, 400), (450, 450, 450))
SINGLE = {"third": THIRD, "slab": SLAB, "column": COLUMN, "small": SMALL}


def part_sql(low: tuple[int, int, int], high: tuple[int, int, int], prefix: str = "") -> str:
    """The same box as a predicate on the gridded cloud with its extents."""
    return " AND ".join(f"{prefix}{a} BETWEEN e{a} * {lo} // 1000 AND e{a} * {hi} // 1000" for a, lo, hi in zip("xyz", low, high, strict=True))
