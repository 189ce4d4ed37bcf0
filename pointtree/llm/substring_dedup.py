"""Substring dedup over a compacted De Bruijn graph of tokens.

The corpus is a graph whose edges are word k-mers. Of every 50-word window only the edge with the least hash is
kept, so that windows with equal words keep the same edge at the same place, and one in about 18 edges is left: these
are the graph's nodes here, joined by the exact stretch of words that leads from one to the next. An aggregate finds
the nodes that more than one document has, and from how many stretches each is entered and left; a join pairs the
ends of stretches that are the only way out of one node and the only way into the other, and pointer doubling by joins
compacts such nonbranching runs to paths. All documents that hold one node of a path hold all of it, so that a path's
first occurrence is the source of each window inside. Windows that reach beyond a path's ends are grouped by
96-bit fingerprints. What is found either way becomes spans with a source document and a place there, and before words
are cut, a span's words are compared with those of its source.

Exact copies of a whole document need no windows: all of theirs start in the first of the copies.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import by_batch, lists, release, rolling, signed, sliding_min, store, stretches, table, text_bytes, word_hashes

WINDOW = 50
#: Words of an edge.
EDGE = 16
EMPTY = hashlib.sha256(b"").hexdigest()
ROW = ["doc_id", "row"]


def _edges(h: np.ndarray, window: int, edge: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every k-mer, and for every window the least of its k-mers' hashes."""
    k = rolling(h, edge)
    return k, sliding_min(k, window - edge + 1)


def _scan(window: int, edge: int):
    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        sizes, digests, least = [], [], []
        for t in text_bytes(b.column(2)):
            words = (t or b"").split()
            sizes.append(len(words))
            digests.append(hashlib.sha256(b" ".join(words)).digest())
            least.append(signed(np.unique(_edges(word_hashes(words), window, edge)[1])) if len(words) >= window else np.empty(0, np.int64))
        return pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), lists(least, pa.int64())], names=[*ROW, "n_words", "digest", "edges"])

    return by_batch(run)


def nodes(h: np.ndarray, known: np.ndarray, window: int, edge: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes -> (place, name, stretch to the next node, words to it) of the nodes that windows keep; 0 where a run ends.

    ``known`` are the repeated edges; a run ends where a window keeps another edge. Of equal edges a window keeps the first.
    """
    k, least = _edges(h, window, edge)
    at = np.flatnonzero(np.isin(least, known))
    if not len(at):
        none = np.zeros(0, np.int64)
        return none, none.view(np.uint64), none.view(np.uint64), none
    place = at + np.lib.stride_tricks.sliding_window_view(k, window - edge + 1)[at].argmin(1)
    first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
    where = place[first]
    # the window before a node's first window keeps the node before it, unless that is not known
    joined = np.flatnonzero(at[first[1:]] == at[first[1:] - 1] + 1)
    stretch, step = np.zeros(len(where), np.uint64), np.zeros(len(where), np.int64)
    stretch[joined] = stretches(h, where[joined], where[joined + 1] + edge)
    step[joined] = where[joined + 1] - where[joined]
    return where, k[where], stretch, step


def _graph(window: int, edge: int):
    """Documents with their repeated edges -> their nodes and the stretches between them."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        places, names, after, before, steps = [], [], [], [], []
        for t, known in zip(text_bytes(b.column(2)), b.column(3).to_pylist(), strict=True):
            where, name, stretch, step = nodes(word_hashes((t or b"").split()), np.array(known, np.int64).view(np.uint64), window, edge)
            places.append(where.astype(np.int32))
            names.append(signed(name))
            after.append(signed(stretch))
            before.append(signed(np.concatenate([stretch[:0], np.zeros(min(1, len(stretch)), np.uint64), stretch[:-1]])))
            steps.append(step.astype(np.int32))
        kinds = [lists(places, pa.int32()), lists(names, pa.int64()), lists(after, pa.int64()), lists(before, pa.int64()), lists(steps, pa.int32())]
        return pa.RecordBatch.from_arrays([*b.columns[:3], *kinds], names=[*ROW, "text", "place", "node", "after", "before", "step"])

    return by_batch(run)


def compact(found: DataFrame, edge: int = EDGE) -> DataFrame:
    """Nodes ``found(doc_id, row, place, node, after, before, step)`` -> ``node, top, at``: the path of each node and its place there.

    A node follows another if that has one way out, this has one way in, and both are the same stretch. Nodes of a
    circle of such stretches are paths of their own.
    """
    ways = found.groupBy("node").agg(F.min("after").alias("a"), F.max("after").alias("z"), F.min("before").alias("b"), F.max("before").alias("y"), F.max("step").alias("step"))
    ways = store(ways.select("node", "step", F.when((F.col("a") == F.col("z")) & (F.col("a") != 0), F.col("a")).alias("out"), F.when((F.col("b") == F.col("y")) & (F.col("b") != 0), F.col("b")).alias("into")), "ways")
    out = ways.where("out is not null").select(F.col("node").alias("top"), F.col("out").alias("stretch"), "step")
    into = ways.where("into is not null").select("node", F.col("into").alias("stretch"))
    after = out.join(into, "stretch").select("node", "top", F.col("step").cast("long").alias("at"))
    p = ways.select("node").join(after, "node", "left").select("node", F.coalesce("top", "node").alias("top"), F.coalesce("at", F.lit(0)).cast("long").alias("at"), F.col("top").isNull().alias("done"))
    p, before = store(p, "paths"), None
    while (left := p.where("not done").count()) and left != before:
        before = left
        far = p.select(F.col("node").alias("top"), F.col("top").alias("top2"), F.col("at").alias("at2"), F.col("done").alias("done2"))
        moved = p.where("not done").join(far, "top").select("node", F.col("top2").alias("top"), (F.col("at") + F.col("at2")).alias("at"), F.col("done2").alias("done"))
        p, old = store(p.where("done").union(moved), "paths"), p
        release(old)
    release(ways)
    return p.select("node", F.when(F.col("done"), F.col("top")).otherwise(F.col("node")).alias("top"), F.when(F.col("done"), F.col("at")).otherwise(0).alias("at"))


def _outside(window: int, edge: int):
    """Documents with their nodes and long paths -> fingerprints of the windows that keep a node and lie in no path."""

    def run(b: pa.RecordBatch) -> pa.RecordBatch:
        starts, first, second = [], [], []
        for t, known, inside in zip(text_bytes(b.column(2)), b.column(3).to_pylist(), b.column(4).to_pylist(), strict=True):
            h = word_hashes((t or b"").split())
            _, least = _edges(h, window, edge)
            open_ = np.isin(least, np.array(known, np.int64).view(np.uint64))
            for p in inside or []:
                open_[max(0, p["start"]) : p["start"] + p["words"] - window + 1] = False
            at = np.flatnonzero(open_)
            starts.append(at.astype(np.int32))
            first.append(signed(rolling(h, window, 0)[at]))
            second.append(signed(rolling(h, window, 1)[at] >> np.uint64(32)).astype(np.int32, casting="unsafe"))
        return pa.RecordBatch.from_arrays([*b.columns[:2], lists(starts, pa.int32()), lists(first, pa.int64()), lists(second, pa.int32())], names=[*ROW, "start", "w1", "w2"])

    return by_batch(run)


def spans(row: np.ndarray, start: np.ndarray, words: np.ndarray, source: np.ndarray, source_row: np.ndarray, there: np.ndarray) -> list[np.ndarray]:
    """Matches of several rows, joined where they overlap or touch at the same distance from one source; the same columns."""
    if not len(row):
        return [row, start, words, source, source_row, there]
    order = np.lexsort((start, there - start, source_row, source, row))
    row, start, words, source, source_row, there = (c[order] for c in (row, start, words, source, source_row, there))
    new = np.ones(len(row), bool)
    new[1:] = np.any([c[1:] != c[:-1] for c in (row, source, source_row, there - start)], axis=0)
    end, far = start + words, np.int64(1) << 32
    reach = np.maximum.accumulate(np.cumsum(new) * far + end) - np.cumsum(new) * far  # the furthest end so far of one source and distance
    new[1:] |= start[1:] > reach[:-1]
    first = np.flatnonzero(new)
    return [row[first], start[first], np.maximum.reduceat(end, first) - start[first], source[first], source_row[first], there[first]]


SPAN = "start int, words int, source long, source_row long, there int"


def _joined(b: pa.RecordBatch) -> pa.RecordBatch:
    found = b.column(2)
    flat = found.flatten()
    at = np.repeat(np.arange(b.num_rows), found.value_lengths().to_numpy())
    columns = [flat.field(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("start", "words", "source", "source_row", "there")]
    at, *columns = spans(at, *columns)
    kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32()]
    return pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), *[pa.array(c).cast(k) for c, k in zip(columns, kinds, strict=True)]], names=[*ROW, "start", "words", "source", "source_row", "there"])


def _pieces(b: pa.RecordBatch) -> pa.RecordBatch:
    """Source documents with the places asked for -> the words there."""
    rows = []
    for doc, row, text, wanted in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), text_bytes(b.column(2)), b.column(3).to_pylist(), strict=True):
        words = (text or b"").split()
        rows += [(doc, row, w["there"], w["words"], b" ".join(words[w["there"] : w["there"] + w["words"]])) for w in wanted]
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()]
    columns = list(zip(*rows)) or [[]] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["source", "source_row", "there", "words", "piece"])


def repeats(docs: DataFrame, window: int = WINDOW, edge: int = EDGE) -> tuple[DataFrame, DataFrame]:
    """(all rows with ``doc_id, row, n_words, digest, copy``, first copies with repeated words: ``doc_id, row, text, found``).

    ``row`` is a hash of the text; ``found`` has the spans with the words of their sources.
    """
    keyed = docs.select("doc_id", F.xxhash64("text").alias("row"), "text")
    scanned = store(keyed.mapInArrow(_scan(window, edge), "doc_id long, row long, n_words long, digest binary, edges array<long>"), "scan")
    long_ = scanned.where((F.col("n_words") >= window) & F.col("doc_id").isNotNull())
    # partial sums take a large group of copies; what is joined back is one row a group, by the document's own id
    firsts = store(long_.groupBy("digest").agg(F.min("doc_id").alias("doc_id")).withColumn("first", F.lit(True)), "firsts")
    marked = scanned.join(firsts, ["doc_id", "digest"], "left").withColumn("first", F.coalesce("first", F.lit(False)))
    edges = store(marked.where("first").select(*ROW, F.explode("edges").alias("edge")), "edges")
    repeated = store(edges.groupBy("edge").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b")).where("a < b").select("edge"), "repeated")
    known = edges.join(repeated, "edge").groupBy(*ROW).agg(F.collect_set("edge").alias("edges"))
    arrays = "place array<int>, node array<long>, after array<long>, before array<long>, step array<int>"
    # repeated rows are one document here
    graph = keyed.join(known, ROW).dropDuplicates(ROW).select(*ROW, "text", "edges").mapInArrow(_graph(window, edge), f"doc_id long, row long, text string, {arrays}")
    graph = store(graph, "graph")
    release(edges, repeated)
    each = graph.select(*ROW, F.explode(F.arrays_zip("place", "node", "after", "before", "step")).alias("n")).select(*ROW, "n.*")
    paths = store(compact(each, edge), "paths")
    placed = store(each.select(*ROW, "place", "node").join(paths, "node").select(*ROW, "top", (F.col("place") - F.col("at")).cast("int").alias("start")).distinct(), "placed")
    long_paths = paths.groupBy("top").agg((F.max("at") + edge).cast("int").alias("words")).where(F.col("words") >= window)
    sources = placed.groupBy("top").agg(F.min(F.struct(*ROW, "start")).alias("s"))
    long_paths = store(long_paths.join(sources, "top").select("top", "words", F.col("s.doc_id").alias("source"), F.col("s.row").alias("source_row"), F.col("s.start").alias("there")), "long")
    inside = store(placed.join(long_paths, "top").select(*ROW, "start", "words", "source", "source_row", "there"), "inside")
    held = inside.groupBy(*ROW).agg(F.collect_list(F.struct("start", "words")).alias("inside"))
    windows = graph.select(*ROW, "text", "node").join(held, ROW, "left").mapInArrow(_outside(window, edge), "doc_id long, row long, start array<int>, w1 array<long>, w2 array<int>")
    windows = store(windows.select(*ROW, F.explode(F.arrays_zip("start", "w1", "w2")).alias("w")).select(*ROW, "w.*"), "windows")
    least = windows.groupBy("w1", "w2").agg(F.min(F.struct(*ROW, "start")).alias("s"), F.max("doc_id").alias("last")).where("s.doc_id < last")
    least = store(least.select("w1", "w2", F.col("s.doc_id").alias("source"), F.col("s.row").alias("source_row"), F.col("s.start").alias("there")), "least")
    again = windows.join(least, ["w1", "w2"]).select(*ROW, "start", F.lit(window).alias("words"), "source", "source_row", "there")
    both = again.union(inside).where("source < doc_id")
    joined = both.groupBy(*ROW).agg(F.collect_list(F.struct("start", "words", "source", "source_row", "there")).alias("f"))
    joined = store(joined.mapInArrow(by_batch(_joined), f"doc_id long, row long, {SPAN}"), "spans")
    release(placed, long_paths, inside, windows, least, paths)
    # the words at the source coordinates, once for each place, however many spans point there
    wanted = joined.select("source", "source_row", "there", "words").distinct().groupBy("source", "source_row").agg(F.collect_list(F.struct("there", "words")).alias("wanted"))
    texts = graph.select(F.col("doc_id").alias("source"), F.col("row").alias("source_row"), "text").hint("merge")
    pieces = store(texts.join(wanted, ["source", "source_row"]).mapInArrow(by_batch(_pieces), "source long, source_row long, there int, words int, piece binary"), "pieces")
    beside = joined.join(pieces.hint("merge"), ["source", "source_row", "there", "words"])
    found = beside.groupBy(*ROW).agg(F.collect_list(F.struct("start", "words", "source", "there", "piece")).alias("found"))
    heads = marked.select(*ROW, "n_words", "digest", (~F.col("first") & (F.col("n_words") >= window) & F.col("doc_id").isNotNull()).alias("copy"))
    return heads, graph.select(*ROW, "text").hint("merge").join(found.hint("merge"), ROW)


def _result(b: pa.RecordBatch) -> pa.RecordBatch:
    """Spans whose words are those of their sources are cut."""
    texts, removed, digests, kept_spans = [], [], [], []
    for t, found in zip(text_bytes(b.column(2)), b.column(3).to_pylist(), strict=True):
        words = (t or b"").split()
        edge, good = np.zeros(len(words) + 1, np.int64), []
        for f in sorted(found, key=lambda f: (f["start"], f["words"])):
            if b" ".join(words[f["start"] : f["start"] + f["words"]]) == f["piece"]:
                edge[f["start"]] += 1
                edge[f["start"] + f["words"]] -= 1
                good.append({k: f[k] for k in ("start", "words", "source", "there")})
        gone = np.cumsum(edge[:-1]) > 0
        joined = b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g])
        texts.append(joined)
        removed.append(int(gone.sum()))
        digests.append(hashlib.sha256(joined).digest())
        kept_spans.append(good)
    kind = pa.list_(pa.struct([("start", pa.int32()), ("words", pa.int32()), ("source", pa.int64()), ("there", pa.int32())]))
    return pa.RecordBatch.from_arrays([*b.columns[:2], pa.array(texts, pa.binary()).cast(pa.string()), pa.array(removed, pa.int64()), pa.array(digests, pa.binary()), pa.array(kept_spans, kind)], names=[*ROW, "kept_text", "n_removed", "kept_digest", "spans"])


RESULT = "doc_id long, row long, kept_text string, n_removed long, kept_digest binary, spans array<struct<start:int,words:int,source:long,there:int>>"


def dedup(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """Per row of ``docs(doc_id, text)``: ``doc_id, n_words, n_removed, kept_sha256, spans``.

    Null and empty texts have no words. Rows with a null doc_id repeat nothing and nothing repeats them. Rows that
    share a doc_id don't repeat each other, whether their texts agree or not. An empty table gives no rows. Exact
    copies of a document are removed whole and have null spans, as have rows that repeat nothing.
    """
    heads, found = repeats(docs, window)
    cut = found.mapInArrow(by_batch(_result, 128), RESULT).drop("kept_text")
    out = heads.join(cut, ROW, "left")
    none = F.coalesce("n_removed", F.lit(0)).cast("long")
    return out.select("doc_id", "n_words", F.when(F.col("copy"), F.col("n_words")).otherwise(none).alias("n_removed"),
                      F.when(F.col("copy"), F.lit(EMPTY)).otherwise(F.lower(F.hex(F.coalesce("kept_digest", "digest")))).alias("kept_sha256"), "spans")


def deduped(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with the repeated words cut from ``text``; rows left without words by that go. Untouched texts stay as they are.

    ``n_chars`` follows the text where ``docs`` has that column. Nulls, ties and empty tables are as in ``dedup``.
    """
    heads, found = repeats(docs, window)
    cut = found.mapInArrow(by_batch(_result, 128), RESULT).where("n_removed > 0").select(*ROW, "kept_text")
    gone = heads.where("copy").select(*ROW).distinct()
    whole = docs.select("doc_id", F.xxhash64("text").alias("row"), F.struct(*docs.columns).alias("doc"))
    left = whole.join(gone, ROW, "left_anti").join(cut.hint("merge"), ROW, "left").where(F.col("kept_text").isNull() | (F.col("kept_text") != ""))
    text = F.coalesce("kept_text", "doc.text")
    new = {"text": text, "n_chars": F.when(F.col("kept_text").isNull(), F.col("doc.n_chars")).otherwise(F.length(text).cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else None}
    return left.select(*[new[c].alias(c) if new.get(c) is not None else F.col("doc")[c].alias(c) for c in docs.columns])


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "documents")).drop("spans")


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
s AS (SELECT doc_id, words, unnest(generate_series(1, len(words) - 49)) AS i FROM w WHERE len(words) >= 50),
h AS (SELECT doc_id, i, md5(array_to_string(words[i:i + 49], ' ')) AS g FROM s),
m AS (SELECT g, min(doc_id) AS first FROM h GROUP BY g),
r AS (SELECT doc_id, i FROM h JOIN m USING (g) WHERE first < doc_id),
x AS (SELECT DISTINCT doc_id, unnest(generate_series(i, i + 49)) AS p FROM r),
c AS (SELECT doc_id, count(*) AS n_removed, list(p) AS gone FROM x GROUP BY doc_id)
SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed,
       sha256(coalesce(array_to_string(CASE WHEN gone IS NULL THEN words ELSE list_transform(list_filter(range(1, len(words) + 1), lambda p: NOT list_contains(gone, p)), lambda p: words[p]) END, ' '), '')) AS kept_sha256
FROM w LEFT JOIN c USING (doc_id)
"""
