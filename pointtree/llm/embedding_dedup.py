"""Near-duplicate vectors: a small-world graph per shard, every shard queried, links verified, components joined.

Equal vectors of a label are one vector with a count. A label's vectors are dealt to shards of bounded size; each shard
gets a graph, and each vector queries all shards of its label. A query whose whole beam links is searched with a wider
one, and beyond ``WIDEST`` against the whole shard, so that no number of links is a limit. Two shards query each other
in one task, so that a link that either side finds counts for both. In each direction a sample of queries is compared
with brute force, until it has shown enough links; until their recall passes, all of its beams are widened.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, release, store, table
from .regions import roots
from .small_world import BATCH, SmallWorld

LEAST_COSINE = 0.93
SHARD = 16_384
BEAM, WIDEST = 48, 768
#: Queries that are audited at first and at most, the true links (none to itself) they should show, and the recall that must be reached.
AUDITED, MOST_AUDITED, LEAST_TRUE, RECALL = 128, 2048, 64, 0.99
#: Slack of single-precision search before the check in double precision.
SLACK = 1e-4


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Vectors as bytes of doubles; null for those that can link with nothing."""
    for b in batches:
        v = b.column("v")
        flat, size = v.flatten(), v.value_lengths().fill_null(0).to_numpy()
        x = flat.fill_null(np.nan).to_numpy(zero_copy_only=False) + 0.0
        ends = np.cumsum(size)
        out, dims = [], []
        for low, high in zip((ends - size).tolist(), ends.tolist(), strict=True):
            part = x[low:high]
            peak = np.abs(part).max() if high > low else 0.0
            ok = peak > 0 and np.isfinite(peak)
            out.append(part.tobytes() if ok else None)
            dims.append(high - low if ok else None)
        yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("label"), pa.array(dims, pa.int32()), pa.array(out, pa.binary())], names=["vec_id", "label", "dim", "v"])


def _matrix(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Raw vectors and unit vectors of a table, in double precision."""
    raw = np.frombuffer(b"".join(t.column("v").to_pylist()), np.float64).reshape(t.num_rows, -1)
    scaled = raw / np.abs(raw).max(1, keepdims=True)
    return raw, scaled / np.linalg.norm(scaled, axis=1, keepdims=True)


def _build(key: tuple, t: pa.Table) -> pa.Table:
    t = t.sort_by("node")
    _, unit = _matrix(t)
    one = lambda v, kind: pa.array([v], kind)
    label, dim, shard = (k.as_py() for k in key)
    return pa.table({"label": one(label, pa.string()), "dim": one(dim, pa.int32()), "shard": one(shard, pa.int32()), "nodes": one(t.column("node").to_numpy().tobytes(), pa.binary()), "counts": one(t.column("n").to_numpy().tobytes(), pa.binary()),
                     "vectors": one(unit.tobytes(), pa.binary()), "graph": one(SmallWorld(unit).to_bytes(), pa.binary())})


class Shard:
    """A shard's vectors, their ids and counts, and the graph over them."""

    def __init__(self, row: dict):
        self.nodes, self.counts = np.frombuffer(row["nodes"], np.int64), np.frombuffer(row["counts"], np.int64)
        self.x = np.frombuffer(row["vectors"], np.float64).reshape(len(self.nodes), -1)
        self.single = self.x.astype(np.float32)
        self.graph = SmallWorld.from_bytes(row["graph"], self.x)

    def __len__(self) -> int:
        return len(self.nodes)

    def near(self, q: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
        """All pairs (query, node) that link, against the whole shard."""
        a, b = np.nonzero(q.astype(np.float32) @ self.single.T >= least - SLACK)
        return self._checked(q, a, b, least)

    def _checked(self, q: np.ndarray, a: np.ndarray, b: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
        good = [np.einsum("nd,nd->n", q[a[k : k + (1 << 16)]], self.x[b[k : k + (1 << 16)]]) >= least for k in range(0, len(a), 1 << 16)]
        good = np.concatenate(good) if good else np.zeros(0, bool)
        return a[good], b[good]

    def search(self, q: np.ndarray, beam: int, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pairs (query, node) that the graph finds to link, and the queries that link with more than the widest beam."""
        pairs, whole = [], []
        for at in range(0, len(q), BATCH):
            rows, width = np.arange(at, min(at + BATCH, len(q))), beam
            while len(rows) and width < min(WIDEST, len(self)):
                ids, sims = self.graph.search(q[rows], width)
                near = (sims >= least - SLACK) & (ids >= 0)
                more = near.all(1)
                a, b = np.nonzero(near & ~more[:, None])
                pairs.append(self._checked(q, rows[a], ids[a, b].astype(np.int64), least))
                rows, width = rows[more], width * 4
            whole.append(rows)
        none = np.zeros(0, np.int64)
        i, j = (np.concatenate([none, *[p[k] for p in pairs]]) for k in (0, 1))
        return i, j, np.concatenate([none, *whole])


def audit(queries: Shard, shard: Shard, least: float) -> tuple[int, int, int]:
    """The beam at which the sample's recall passes, its true links and those found of them."""
    same, n = queries is shard, len(queries)
    order = np.random.default_rng(n).permutation(n)
    want, m, done = set(), min(AUDITED, n), 0
    while True:
        a, b = shard.near(queries.x[order[done:m]], least)
        want |= {(int(i), int(j)) for i, j in zip(order[done:m][a], b, strict=True) if not (same and i == j)}
        if len(want) >= LEAST_TRUE or m >= min(n, MOST_AUDITED):
            break
        done, m = m, min(2 * m, n)
    rows, beam, found = order[:m], BEAM, len(want)
    while want and beam < len(shard):
        i, j, whole = shard.search(queries.x[rows], beam, least)
        got = set(zip(rows[i].tolist(), j.tolist(), strict=True))
        exact = set(rows[whole].tolist())
        found = sum(w in got or w[0] in exact for w in want)
        if found >= RECALL * len(want):
            break
        beam *= 2
        found = len(want)
    return beam, len(want), found


def _linked(a: Shard, b: Shard, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[tuple[int, int, int]]]:
    """Links of two shards, or of one with itself: counts for both, least members of components (a's, then b's), audits."""
    same, n = a is b, len(b)
    counts = [np.zeros(len(a), np.int64), np.zeros(n, np.int64)]
    size = len(a) + (0 if same else n)
    label, shift = np.arange(size), 0 if same else len(a)
    codes, dense, audits = [], [], []
    for q, x, turned in ((a, b, False), (b, a, True))[: 1 if same else 2]:
        beam, true, found = audit(q, x, least)
        audits.append((beam, true, found))
        i, j, whole = x.search(q.x, beam, least)
        codes.append(j * n + i if turned else i * n + j)
        dense.append(np.isin(np.arange(len(q)), whole))
    full_a, full_b = dense[0], dense[-1]

    def join(i: np.ndarray, j: np.ndarray) -> None:
        nonlocal label
        if len(i):
            label = roots(size, np.concatenate([i, np.arange(size)]), np.concatenate([j + shift, label]))

    # those that link with more than a beam holds: their links are all known, and tell the other side's
    for side, (q, x, full, other) in enumerate(((a, b, full_a, full_b), (b, a, full_b, full_a))[: 1 if same else 2]):
        rows = np.flatnonzero(full)
        for at in range(0, len(rows), BATCH):
            part = rows[at : at + BATCH]
            i, j = x.near(q.x[part], least)
            i = part[i]
            if same:
                i, j = i[i != j], j[i != j]
            np.add.at(counts[side], i, x.counts[j])
            join(*((j, i) if side else (i, j)))
            i, j = i[~other[j]], j[~other[j]]
            codes.append(j * n + i if side else i * n + j)
    code = np.unique(np.concatenate([np.zeros(0, np.int64), *codes]))
    i, j = code // n, code % n
    if same:
        code = np.unique(np.concatenate([i[i != j] * n + j[i != j], j[i != j] * n + i[i != j]]))
        i, j = code // n, code % n
        np.add.at(counts[0], i[~full_a[i]], b.counts[j[~full_a[i]]])
    else:
        np.add.at(counts[0], i[~full_a[i]], b.counts[j[~full_a[i]]])
        np.add.at(counts[1], j[~full_b[j]], a.counts[i[~full_b[j]]])
    join(i, j)
    return counts[0], counts[1], label, audits


FOUND = "label string, dim int, node long, n_links long, root long, beam int, true_links long, found_links long"


def _query(least: float):
    def run(key: tuple, t: pa.Table) -> pa.Table:
        shards = [Shard(r) for r in t.to_pylist()]
        a, b = shards[0], shards[-1]
        left, right, top, audits = _linked(a, b, least)
        nodes = a.nodes if a is b else np.concatenate([a.nodes, b.nodes])
        counts = left if a is b else np.concatenate([left, right])
        moved = np.flatnonzero(top != np.arange(len(top)))
        n, m, k = len(nodes), len(moved), len(audits)
        column = lambda parts, kind: pa.array([x for p in parts for x in p], kind)
        return pa.table({
            "label": pa.array([key[0].as_py()] * (n + m + k), pa.string()), "dim": pa.array([key[1].as_py()] * (n + m + k), pa.int32()),
            "node": column((nodes.tolist(), nodes[moved].tolist(), [None] * k), pa.int64()), "n_links": column((counts.tolist(), [0] * m, [None] * k), pa.int64()),
            "root": column(([None] * n, nodes[top[moved]].tolist(), [None] * k), pa.int64()),
            **{name: column(([None] * (n + m), [x[c] for x in audits]), kind) for c, (name, kind) in enumerate((("beam", pa.int32()), ("true_links", pa.int64()), ("found_links", pa.int64())))}})

    return run


def _searched(vectors: DataFrame, least: float, shard: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows with their unit vectors, distinct vectors with their nodes, and what the shards' queries found."""
    typed = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("string").alias("label"), F.col("embedding").cast("array<double>").alias("v"))
    units = store(typed.mapInArrow(_units, "vec_id long, label string, dim int, v binary"), "units")
    able = units.where("vec_id is not null and label is not null and v is not null")
    reps = store(able.groupBy("label", "dim", "v").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n")), "reps")
    # a node per distinct vector: its least id, or a hash where that names vectors that differ
    twice = reps.groupBy("rep").agg(F.count("*").alias("k")).where("k > 1").select("rep", F.lit(True).alias("twice"))
    reps = store(reps.join(twice, "rep", "left").withColumn("node", F.when(F.col("twice"), F.xxhash64("label", "dim", "v")).otherwise(F.col("rep"))).drop("twice"), "nodes")
    shards = store(reps.groupBy("label", "dim").agg(F.ceil(F.count("*") / shard).cast("int").alias("shards")), "shards")
    dealt = reps.join(shards, ["label", "dim"]).withColumn("shard", F.pmod(F.xxhash64("node"), F.col("shards")).cast("int"))
    index = store(dealt.select("label", "dim", "shard", "node", "n", "v").groupBy("label", "dim", "shard").applyInArrow(_build, "label string, dim int, shard int, nodes binary, counts binary, vectors binary, graph binary"), "index")
    every = F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("other")
    met = index.hint("merge").join(shards, ["label", "dim"]).select("label", "dim", "shard", "nodes", "counts", "vectors", "graph", every)
    met = met.select("label", "dim", F.least("shard", "other").alias("low"), F.greatest("shard", "other").alias("high"), "nodes", "counts", "vectors", "graph")
    found = store(met.groupBy("label", "dim", "low", "high").applyInArrow(_query(least), FOUND), "found")
    release(index, shards)
    return units, reps, found


def audits(vectors: DataFrame, least: float = LEAST_COSINE, shard: int = SHARD) -> DataFrame:
    """``label, dim, beam, true_links, found_links`` per audited direction of two shards."""
    return _searched(vectors, least, shard)[2].where("beam is not null").select("label", "dim", "beam", "true_links", "found_links")


def links(vectors: DataFrame, least: float = LEAST_COSINE, shard: int = SHARD) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` per row of ``vectors(vec_id, embedding, label)``.

    Rows with a null id or label, and vectors that are null, empty, zero or hold null or non-finite components, link
    with nothing and are kept. Vectors of different lengths are not compared. Repeated rows, and rows that share an id
    under other labels or with other vectors, are vectors like others. An empty table gives no rows.
    """
    units, reps, found = _searched(vectors, least, shard)
    joined = components(found.where("root is not null").select(F.col("node").alias("a"), F.col("root").alias("b")))
    sums = found.where("node is not null").groupBy("node").agg(F.sum("n_links").alias("n_links"))
    named = reps.join(joined.select(F.col("id").alias("node"), F.col("component").alias("root")), "node", "left").withColumn("root", F.coalesce("root", "node"))
    named = store(named, "named")
    lowest = named.groupBy("root").agg(F.min("rep").alias("component"))
    per = named.join(lowest, "root").join(sums, "node").select("label", "dim", "v", (F.col("n_links") + F.col("n") - 1).alias("n_links"), "component")
    per = store(per, "per")
    release(found, named, reps)
    out = units.withColumn("v", F.when(F.col("vec_id").isNotNull(), F.col("v"))).join(per, ["label", "dim", "v"], "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.when(F.col("vec_id").isNotNull(), F.coalesce("component", "vec_id")).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op2_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return links(table(spark, sf_dir, "embeddings"))


ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, label, list_transform(embedding, lambda e: CAST(e AS DOUBLE)) AS x FROM embeddings),
e AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.93),
r AS (SELECT a AS id, a AS reach FROM e UNION SELECT r.id, e.b FROM r JOIN e ON r.reach = e.a),
c AS (SELECT id, min(reach) AS component FROM r GROUP BY id),
n AS (SELECT a, count(*) AS n FROM e GROUP BY a)
SELECT vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, coalesce(c.component, vec_id) AS component_id, coalesce(c.component, vec_id) = vec_id AS kept
FROM v LEFT JOIN c ON c.id = vec_id LEFT JOIN n ON n.a = vec_id
"""
