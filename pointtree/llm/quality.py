"""Quality rules: fixed base rules, then robust multivariate outliers per language and source.

Each text is told by a few statistics on transformed scales. A minimum-covariance-determinant estimate is fitted
to every group of language and source over all of its rows that pass the base rules. There are several starts: the
rows nearest to the medians, in units of absolute deviations from them or of quartiles, all rows, and a tenth of them.
A concentration step estimates centre and covariance of the part of the rows with the least distances; after
two of these the start with the least determinant goes on, until its determinant no longer falls. Every step is
one aggregate with partial sums, so that a hot group costs no task more than others.

Symbols, repeated lines and repeated words are 0 in most texts, so that the kept rows may not vary in them at all.
Counts tell how much a rate is uncertain even so: the square root of a Poisson count varies by 1/4. The mean of that over
the kept rows is the least variance of the three rates; the other two have a ridge against singular matrices only.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import by_batch, release, rolling, store, table, text_bytes, word_hashes

SYMBOLS = b"#*$%&|<>"
BLANK = b" \t\n\x0b\x0c\r"
REPEAT_WINDOW = 8
#: Fixed values of the base rules: least words, most per cent of words in repeated windows.
LEAST_WORDS, MOST_REPEATED = 20, 30
#: Rows that pass the base rules that a group needs for an estimate of its own; smaller ones are judged by that of all rows of their language, then of all rows.
LEAST_ROWS = 100
#: Part of the rows that a concentration step keeps, the steps of all starts, the fall of a log-determinant that counts,
#: and the largest squared distance kept (what one row in 10,000 of a normal cloud exceeds).
KEPT_PART, STEPS, FALL, MOST_DISTANCE = 0.75, 2, 1e-3, 25.745
#: The start from a part of the rows takes one in so many, by a hash of their statistics.
TENTH = 10
X = ["x_words", "x_length", "x_symbols", "x_lines", "x_repeats"]
#: Added to the least variances, so that every covariance has an inverse.
RIDGE = 1e-6
#: Distance between the quartiles of a standard normal distribution, and the median of its absolute deviations.
QUARTILES, DEVIATIONS = 1.3489795003921634, 0.6744897501960817
#: Variance of the square root of a Poisson count.
ROOT_VARIANCE = 0.25
#: Medians of the chi-squared distributions with one to five degrees of freedom.
CHI_MEDIANS = (0.454936423119573, 1.386294361119891, 2.365973884375338, 3.356693980033321, 4.351460191095529)
CONT = bytes(range(0x80, 0xC0))


def statistics(raw: bytes | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of one text."""
    if not raw:
        return 0, 0, 0, 0, 0
    words = raw.split()
    n = len(words)
    chars = len(raw.translate(None, BLANK + CONT))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    lines, dup = raw.split(b"\n"), 0
    if len(lines) > 1 and len(set(lines)) < len(lines):
        seen = set()
        for line in lines:
            if line in seen:
                dup += bool(line.strip())
            else:
                seen.add(line)
    repeated = 0
    if n > REPEAT_WINDOW:
        h = rolling(word_hashes(words), REPEAT_WINDOW)
        order = np.sort(h)
        if (order[1:] == order[:-1]).any():
            _, inverse, counts = np.unique(h, return_inverse=True, return_counts=True)
            starts = np.flatnonzero(counts[inverse] > 1)
            edge = np.zeros(n + 1, np.int64)
            np.add.at(edge, starts, 1)
            np.add.at(edge, starts + REPEAT_WINDOW, -1)
            repeated = int((np.cumsum(edge[:-1]) > 0).sum())
    return n, chars, symbols, dup, repeated


BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def base(docs: DataFrame) -> DataFrame:
    """``doc_id, lang, source`` with the base statistics, ``base_failed`` and the transformed statistics."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        got = [statistics(t) for t in text_bytes(b.column(3))]
        columns = [pa.array(c, pa.int64()) for c in zip(*got)] or [pa.array([], pa.int64())] * 5
        return pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), *columns], names=["doc_id", "lang", "source", *BASE])

    out = docs.select("doc_id", F.col("lang").cast("string"), F.col("source").cast("string"), "text").mapInArrow(by_batch(run), "doc_id long, lang string, source string, " + ", ".join(f"{c} long" for c in BASE))
    words = F.greatest("n_words", F.lit(1))
    return out.withColumns({
        "base_failed": (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words")),
        "x_words": F.log1p("n_words"),
        "x_length": F.log1p(F.col("word_chars") / words),
        "x_symbols": F.sqrt(F.col("n_symbols") / F.greatest("word_chars", F.lit(1))),
        "x_lines": F.sqrt(F.col("n_dup_lines") / words),
        "x_repeats": F.sqrt(F.col("n_repeat_words") / words),
        "per_word": 1 / words,
        "per_char": 1 / F.greatest("word_chars", F.lit(1)),
    })


def _pairs() -> list[tuple[int, int]]:
    return [(i, j) for i in range(len(X)) for j in range(i, len(X))]


def _least(per_word, per_char) -> list:
    """Least variance of each statistic, from the means of 1/words and 1/characters; repeated words come by windows."""
    return [RIDGE, RIDGE, ROOT_VARIANCE * per_char + RIDGE, ROOT_VARIANCE * per_word + RIDGE, ROOT_VARIANCE * REPEAT_WINDOW * per_word + RIDGE]


def estimate(mean: np.ndarray, cov: np.ndarray, least: np.ndarray, median: float | None = None) -> tuple[np.ndarray, float]:
    """Inverse and log-determinant of a covariance whose variances are at least ``least``.

    The kept rows' covariance is too small; ``median``, that of all rows' distances, tells by which factor.
    """
    degrees = int((np.diag(cov) > least).sum())
    if degrees and median is not None:
        cov = cov * max(1.0, median / CHI_MEDIANS[degrees - 1])
    cov = cov + np.diag(np.maximum(0, least - np.diag(cov)) + RIDGE)
    return np.linalg.inv(cov), float(np.linalg.slogdet(cov)[1])


STATE = "grp string, k int, centre array<double>, inverse array<double>, cov array<double>, least array<double>, fall double"


def _fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of the kept rows per group and start -> the next estimate."""
    for b in batches:
        out: dict[str, list] = {c.split()[0]: [] for c in STATE.split(", ")}
        for r in b.to_pylist():
            mean = np.array([r[f"s{i}"] for i in range(len(X))]) / r["n"]
            cov = np.empty((len(X), len(X)))
            for i, j in _pairs():
                cov[i, j] = cov[j, i] = r[f"s{i}_{j}"] / r["n"] - mean[i] * mean[j]
            least = np.array(_least(r["mean_per_word"], r["mean_per_char"]))
            inverse, size = estimate(mean, cov, least)
            for c, v in zip(out, (r["grp"], r["k"], mean.tolist(), inverse.ravel().tolist(), cov.ravel().tolist(), least.tolist(), size), strict=True):
                out[c].append(v)
        kinds = [pa.string(), pa.int32(), *[pa.list_(pa.float64())] * 4, pa.float64()]
        yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out.values(), kinds, strict=True)], names=list(out))


def _scaled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Estimates with the median distance of all rows -> centre and inverse covariance that distances are taken by."""
    for b in batches:
        rows = b.to_pylist()
        size = len(X)
        inverses = [estimate(np.array(r["centre"]), np.array(r["cov"]).reshape(size, size), np.array(r["least"]), r["median"])[0].ravel().tolist() for r in rows]
        kind = pa.list_(pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array([r["grp"] for r in rows], pa.string()), pa.array([r["centre"] for r in rows], kind), pa.array(inverses, kind)], names=["grp", "centre", "inverse"])


def _distance() -> F.Column:
    d = [F.col(x) - F.col("centre")[i] for i, x in enumerate(X)]
    return sum((d[i] * d[j] * F.col("inverse")[i * len(X) + j] * (1 if i == j else 2) for i, j in _pairs()), F.lit(0.0))


def _beside(rows: DataFrame, terms: DataFrame, *on: str) -> DataFrame:
    """Rows with their group's terms; broadcast while there are few groups, else a join whose hot side can be split."""
    return rows.join(F.broadcast(terms) if terms.count() <= 20_000 else terms, list(on))


def _sums(kept: DataFrame) -> DataFrame:
    means = [F.avg("per_word").alias("mean_per_word"), F.avg("per_char").alias("mean_per_char")]
    return kept.groupBy("grp", "k").agg(F.count("*").alias("n"), *means, *[F.sum(x).alias(f"s{i}") for i, x in enumerate(X)], *[F.sum(F.col(X[i]) * F.col(X[j])).alias(f"s{i}_{j}") for i, j in _pairs()])


def _concentrated(far: DataFrame) -> DataFrame:
    """Rows with their distance ``d`` per group and start ``k`` -> the estimates of the part with the least distances."""
    quantile = store(far.groupBy("grp", "k").agg(F.percentile_approx("d", KEPT_PART, 2000).alias("q")), "quantile")
    out = store(_sums(_beside(far, quantile, "grp", "k").where("d <= q")).mapInArrow(_fitted, STATE), "state")
    release(quantile)
    return out


def determinants(rows: DataFrame) -> DataFrame:
    """The estimate with the least determinant per group of ``rows(grp, statistics, per_word, per_char)``."""
    means = [F.avg("per_word").alias("mean_per_word"), F.avg("per_char").alias("mean_per_char")]
    half = store(rows.groupBy("grp").agg(*[F.percentile_approx(x, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 2000).alias(f"m_{x}") for x in X], *means), "half")
    at = _beside(rows, half, "grp")
    off = {x: F.abs(F.col(x) - F.col(f"m_{x}")[1]) for x in X}
    absolute = store(at.groupBy("grp").agg(*[F.percentile_approx(off[x], 0.5, 2000).alias(f"a_{x}") for x in X]), "absolute")
    at = _beside(at, absolute, "grp")
    least = _least(F.col("mean_per_word"), F.col("mean_per_char"))
    by = lambda spread: sum((off[x] ** 2 / F.greatest(spread(x) ** 2, F.lit(v)) for x, v in zip(X, least, strict=True)), F.lit(0.0))
    tenth = F.when(F.pmod(F.xxhash64(*X), F.lit(TENTH)) == 0, 0.0)
    starts = [by(lambda x: F.col(f"a_{x}") / DEVIATIONS), by(lambda x: (F.col(f"m_{x}")[2] - F.col(f"m_{x}")[0]) / QUARTILES), F.lit(0.0), tenth]
    each = at.select("grp", *X, "per_word", "per_char", F.posexplode(F.array(*starts)).alias("k", "d")).where("d is not null")
    state = _concentrated(each)
    far = lambda now, of: _beside(of, now, "grp").withColumn("d", _distance())
    for _ in range(STEPS - 1):
        state = _concentrated(far(state.select("grp", "k", "centre", "inverse"), rows))
    best = state.groupBy("grp").agg(F.min(F.struct("fall", "k", "centre", "inverse", "cov", "least")).alias("b")).select("grp", "b.k", "b.centre", "b.inverse", "b.cov", "b.least", "b.fall")
    done, going = None, store(best, "state")
    while True:  # a determinant has a least value, since variances have, and falls by a part each time
        of = _beside(rows, going.select("grp"), "grp")
        new = _concentrated(far(going.select("grp", "k", "centre", "inverse"), of))
        old = going.select("grp", F.col("fall").alias("before"))
        fell = store(new.join(old, "grp").withColumn("fell", F.col("fall") < F.col("before") - FALL), "fell")
        still = going.join(fell.where("not fell").select("grp"), "grp", "left_semi")
        done = still if done is None else done.unionByName(still)
        going = store(fell.where("fell").drop("fell", "before"), "state")
        if going.isEmpty():
            return done


def rules(docs: DataFrame) -> DataFrame:
    """Base statistics and verdict per row of ``docs(doc_id, text, lang, source)``.

    Null texts have no words and fail the base rules, as do empty ones. Null languages and sources are groups of their
    own. Repeated rows count as often as they occur. Where not even all rows together reach ``LEAST_ROWS``, rows
    that pass the base rules are kept. An empty table gives no rows.
    """
    b = store(base(docs), "quality")
    good = b.where("not base_failed")
    by_both = good.groupBy("lang", "source").agg(F.count("*").alias("n"))
    by_lang = by_both.groupBy("lang").agg(F.sum("n").alias("n_lang"), F.min("n").alias("least"))
    name = lambda c: F.coalesce(F.concat(F.lit("="), c), F.lit("null"))
    own, pooled = F.concat_ws("\x00", F.lit("2"), name("lang"), name("source")), F.concat_ws("\x00", F.lit("1"), name("lang"))
    large, common = F.col("n") >= LEAST_ROWS, F.col("n_lang") >= LEAST_ROWS
    named = by_both.join(by_lang.withColumnRenamed("lang", "l"), F.col("lang").eqNullSafe(F.col("l"))).select(
        F.col("lang").alias("g_lang"), F.col("source").alias("g_source"), "n",
        F.when(large, own).when(common, pooled).otherwise("0").alias("grp"),
        F.when(large, own).alias("fit_own"), F.when(common & (F.col("least") < LEAST_ROWS), pooled).alias("fit_lang"))
    groups = store(named, "groups")
    few = groups.count() <= 20_000
    enough = (groups.agg(F.sum("n")).first()[0] or 0) >= LEAST_ROWS
    over_all = F.lit("0") if enough and groups.where("grp = '0'").limit(1).count() else F.lit(None).cast("string")
    # a row counts in its own group's estimate and in those that smaller groups beside it are judged by
    fits = F.explode(F.array_compact(F.array("fit_own", "fit_lang", over_all))).alias("grp")
    rows = store(good.join(F.broadcast(groups) if few else groups, F.col("lang").eqNullSafe(F.col("g_lang")) & F.col("source").eqNullSafe(F.col("g_source"))).select(fits, *X, "per_word", "per_char"), "rows")
    state = store(determinants(rows), "determinants")
    far = _beside(rows, state.select("grp", "centre", "inverse"), "grp").withColumn("d", _distance())
    median = far.groupBy("grp").agg(F.percentile_approx("d", 0.5, 2000).alias("median"))
    terms = store(state.join(median, "grp").mapInArrow(_scaled, "grp string, centre array<double>, inverse array<double>"), "terms")
    release(rows)
    verdict = groups.join(terms, "grp", "left")
    out = b.join(F.broadcast(verdict) if few else verdict, F.col("lang").eqNullSafe(F.col("g_lang")) & F.col("source").eqNullSafe(F.col("g_source")), "left")
    out = out.withColumn("distance", F.when(~F.col("base_failed"), _distance()))
    return out.select("doc_id", *BASE, "base_failed", (~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= MOST_DISTANCE)).alias("kept"), "distance")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules(table(spark, sf_dir, "documents"))
