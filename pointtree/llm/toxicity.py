"""Toxicity: boosted trees over dense features of whole texts, calibrated by isotonic regression.

Features are densities of two lexicons (a fixed list of insults and the words that the labelled sample itself shows
to be toxic), how near the second person stands to them, capitals, punctuation and rates of obfuscated words.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .boosting import Boosted, Isotonic
from .common import Bounded, begin, by_batch, lists, release, store, table, text_bytes

#: Words of insult and of address in the languages of the corpus.
INSULTS = frozenset("""
idiot idiots idiotic moron morons moronic stupid dumb dumbass fool fools scum trash garbage worthless pathetic disgusting filthy filth
loser losers clown clowns jerk jerks creep creeps freak freaks pig pigs vermin parasite parasites rat rats ugly hate hated kill die
shut damn hell crap shit shitty bullshit bastard bastards bitch bitches ass asshole assholes fuck fucking fucked fucker dick prick slut
whore retard retarded imbecile imbeciles cretin degenerate degenerates lunatic nasty vile despicable useless braindead clueless coward liar
dumm dummkopf idioten trottel arschloch scheisse scheiße wertlos abschaum versager ekelhaft widerlich drecksack hurensohn
connard connards connasse imbécile débile salaud salope merde ordure minable dégoûtant crétin abruti pourriture
estúpido estúpida imbécil idiota idiotas basura escoria asqueroso patético inútil mierda cabrón puta gilipollas payaso
""".split())
YOU = frozenset("you your yours yourself yourselves u ur youre du dein deine deinen dir dich ihr euch tu toi ton ta tes vous votre vos tú ti tus vosotros usted ustedes".split())
LEET = str.maketrans("013457@$!|", "oieastasii")
EDGE = re.compile(r"^\W+|\W+$")
FEATURES = 16
#: Bounds of the labelled sample that the model is fitted on and of the learned lexicon; the rows, and the part of the
#: toxic rows, in which a learned word occurs at least: what only a group of copies holds is no sign of toxicity.
SAMPLE_ROWS, LEARNED_WORDS, LEAST_ROWS, LEAST_PART = 20_000, 200, 8, 0.03
THRESHOLD = 0.7
#: Texts that are turned into Python objects at once.
ROWS = 512
#: Words between an insult and a second person that still count as near.
NEAR = 5
#: Bytes of classified words that a worker keeps.
CACHE_BYTES = 32 << 20
UPPER = bytes(range(65, 91))
LOWER = bytes(range(97, 123))
PUNCTUATION = b".,;:!?'\"()-"
SYMBOLS = b"#*$%&|<>@^~_+={}[]\\/"


def plain(word: bytes) -> str:
    return EDGE.sub("", word.decode("utf-8", "replace").lower())


class Classes(Bounded):
    """A raw word -> bits: 1 insult, 2 learned, 4 second person, 8 obfuscated insult, 16 obfuscated word, 32 all capitals."""

    def __init__(self, learned: frozenset[str]):
        super().__init__(CACHE_BYTES)
        self.learned = learned
        self.hidden = INSULTS | learned

    def __missing__(self, word: bytes) -> int:
        p = plain(word)
        bits = (p in INSULTS) | 2 * (p in self.learned) | 4 * (p in YOU)
        if not bits and p and not p.isalpha():
            clean = re.sub(r"[^\w]|_", "", p.translate(LEET))
            mixed = any(c.isalpha() for c in p)
            bits |= 8 * (mixed and clean in self.hidden) | 16 * (mixed and bool(re.search(r"\w[^\w\s'’-]+\w|[a-z]\d+[a-z]", p)))
        if len(word) > 2 and word.isupper():
            bits |= 32
        self.keep(word, bits)
        return bits


def features(raw: bytes | None, classes: Classes) -> np.ndarray:
    """The dense features of one text; an empty or null text has zeros."""
    out = np.zeros(FEATURES)
    words = raw.split() if raw else []
    n = len(words)
    if not n:
        return out
    bits = np.fromiter(map(classes.__getitem__, words), np.uint8, n)
    insult, learned, you, hidden = bits & 1 > 0, bits & 2 > 0, bits & 4 > 0, bits & 8 > 0
    bad = insult | learned | hidden
    hits = np.flatnonzero(bad)
    near = densest = 0
    if len(hits):
        second = np.flatnonzero(you)
        if len(second):
            at = np.searchsorted(second, hits)
            gap = np.minimum(np.abs(second[np.minimum(at, len(second) - 1)] - hits), np.abs(hits - second[np.maximum(at - 1, 0)]))
            near = int((gap <= NEAR).sum())
        densest = int((np.searchsorted(hits, hits + 50) - np.arange(len(hits))).max())
    size = len(raw)
    count = lambda chars: size - len(raw.translate(None, chars))
    letters = count(UPPER + LOWER) or 1
    out[:] = (insult.sum() / n, np.log1p(insult.sum()), learned.sum() / n, np.log1p(learned.sum()), hidden.sum() / n, (bits & 16 > 0).sum() / n, near / n, np.log1p(near), you.sum() / n,
              count(UPPER) / letters, (bits & 32 > 0).sum() / n, raw.count(b"!") / n, raw.count(b"?") / n, count(PUNCTUATION) / size, count(SYMBOLS) / size, densest)
    return out


def held_out(doc_id: str = "doc_id") -> F.Column:
    """Rows whose labels are never learned from."""
    return F.crc32(F.col(doc_id).cast("string")) % 3 == 1


def _sample(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Up to ``SAMPLE_ROWS`` labelled rows that are not held out: those with the least hashes of their ids."""
    some = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAMPLE_ROWS)
    # of rows that share an id the least text is taken, so that the bound holds for texts as well
    rows = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    return store(rows, "sample")


def _distinct_words(b: pa.RecordBatch) -> pa.RecordBatch:
    words = [sorted({p for w in set((t or b"").split()) if (p := plain(w)).isalpha()}) for t in text_bytes(b.column(0))]
    return pa.RecordBatch.from_arrays([pa.array(words, pa.list_(pa.string())), b.column(1)], names=["words", "toxic"])


def learn_words(sample: DataFrame) -> frozenset[str]:
    """Words of the sample that occur in enough toxic rows and far more often there than elsewhere."""
    rows = sample.select("text", F.col("toxic").cast("int").alias("toxic")).mapInArrow(by_batch(_distinct_words), "words array<string>, toxic int")
    n = rows.agg(F.sum("toxic"), F.sum(1 - F.col("toxic"))).first()
    if not n[0] or not n[1]:
        return frozenset()
    counted = rows.select(F.explode("words").alias("w"), "toxic").groupBy("w").agg(F.sum("toxic").alias("t"), F.sum(1 - F.col("toxic")).alias("c"))
    odds = (F.col("t") / n[0]) / ((F.col("c") + 0.5) / n[1])
    top = counted.where((F.col("t") >= max(LEAST_ROWS, LEAST_PART * n[0])) & (odds >= 8)).orderBy(odds.desc(), F.col("t").desc(), "w").limit(LEARNED_WORDS)
    return frozenset(r["w"] for r in top.select("w").collect())


class Scorer:
    """A fitted model: learned words, trees and calibration."""

    def __init__(self, learned: frozenset[str], x: np.ndarray, y: np.ndarray):
        self.learned = learned
        self.trees = Boosted().fit(x, y)
        raw = np.zeros(len(y))
        for k in range(3):  # calibrated on scores of trees that have not seen the row
            out = np.arange(len(y)) % 3 == k
            raw[out] = Boosted().fit(x[~out], y[~out]).raw(x[out]) if out.any() and (~out).any() else 0
        self.calibration = Isotonic().fit(raw, y)
        self.classes: Classes | None = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"classes": None}

    def features(self, texts: list[bytes | None]) -> np.ndarray:
        if self.classes is None:
            self.classes = Classes(self.learned)
        return np.stack([features(t, self.classes) for t in texts]) if texts else np.zeros((0, FEATURES))

    def score(self, texts: list[bytes | None]) -> np.ndarray:
        return np.clip(self.calibration(self.trees.raw(self.features(texts))), 0.0, 1.0) if texts else np.zeros(0)


def fit(docs: DataFrame, labels: DataFrame) -> Scorer:
    """Fit on the bounded labelled sample; only its features come to the driver. Without labels every score is near 0."""
    sample = _sample(docs, labels)
    learned = learn_words(sample)

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        classes = Classes(learned)
        x = [features(t, classes) for t in text_bytes(b.column(1))]
        return pa.RecordBatch.from_arrays([b.column(0), lists(x, pa.float64()), b.column(2)], names=["doc_id", "x", "toxic"])

    rows = sample.select("doc_id", "text", F.col("toxic").cast("int").alias("toxic")).mapInArrow(by_batch(run, 2048), "doc_id long, x array<double>, toxic int").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["x"]))
    release(sample)
    x = np.array([r["x"] for r in rows]).reshape(-1, FEATURES)
    return Scorer(learned, x, np.array([r["toxic"] for r in rows], float))


def scorer(docs: DataFrame, labels: DataFrame) -> Callable[[str], F.Column]:
    """A function from the name of a text column to its score, fitted on ``docs`` and ``labels``; only texts go to Python.

    Null and empty texts are scored as texts without words.
    """
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))

    @F.arrow_udf("double")
    def run(texts: pa.Array) -> pa.Array:
        begin()
        at = range(0, len(texts), ROWS)
        return pa.array(np.concatenate([shared.value.score(text_bytes(texts.slice(k, ROWS))) for k in at] or [np.zeros(0)]), pa.float64())

    return run


def score(docs: DataFrame, labels: DataFrame, keep: list[str]) -> DataFrame:
    """Columns ``keep`` of ``docs`` with ``tox_score``. Repeated rows get equal scores; an empty table gives no rows."""
    return docs.select(*keep, scorer(docs, labels)("text").alias("tox_score"))


def clean(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Rows of ``docs`` that are not rejected, with the columns of ``docs``; null and empty texts have no words and stay."""
    return docs.where(scorer(docs, labels)("text") < threshold)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ["doc_id"])
    return s.select("doc_id", held_out().alias("held_out"), F.col("tox_score").alias("score"), (F.col("tox_score") >= THRESHOLD).cast("int").alias("predicted"))
