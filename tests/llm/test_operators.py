"""The operators on small tables with nulls, empty and long texts, ties, repeated rows and clashing columns, against brute force."""

import hashlib
import itertools
import random
import re
import uuid
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from pointtree.llm import embedding_dedup, html_text, jaccard_join, mixing, packing, quality, registry, substring_dedup, token_store, toxicity, warc
from pointtree.llm.common import components, shared_dir
from pointtree.llm.encoding import encoder, tokenizer_path

def folder(spark):
    return f"{shared_dir(spark)}/test-{uuid.uuid4().hex}"


WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, size int, key string, `first` string"


def corpus():
    r = random.Random(7)
    words = ["w%d" % i for i in range(400)]
    make = lambda n: " ".join(r.choice(words) for _ in range(n))
    base, passage = make(150), make(60)
    near = base.split()
    near[70] = "changed"
    texts = [base, base, " ".join(near), "  " + base.replace(" ", "\n", 3), make(40) + " " + passage + " " + make(9), passage, make(12) + "\t" + passage, make(3000), None, "", " \n ", "one", "one", "A b", "a B", make(30)]
    texts += [passage + " " + passage, make(20) + "\xa0　end", "x " * 100]
    rows = [(i, t, ["en", None, "de"][i % 3], ["a", "b", None][i % 3], len(t) if t else None, 1, "k", None) for i, t in enumerate(texts)]
    rows += [rows[2], rows[5], (None, base, None, "a", 5, 1, "k", None), (None, None, None, None, None, None, None, None)]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus(), DOCS).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def words(t):
    return WORD.findall(t or "")


def brute_repeats(rows, window=50):
    first = {}
    for d, t in rows:
        w = words(t)
        for i in range(len(w) - window + 1):
            k = tuple(w[i : i + window])
            if d is not None:
                first[k] = min(first.get(k, d), d)
    out = []
    for d, t in rows:
        w = words(t)
        gone = set()
        for i in range(len(w) - window + 1):
            if d is not None and first[tuple(w[i : i + window])] < d:
                gone |= set(range(i, i + window))
        kept = [x for i, x in enumerate(w) if i not in gone]
        out.append((d, len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def test_substring_dedup(docs, none):
    got = substring_dedup.dedup(docs).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()
    assert sorted(map(tuple, got), key=str) == brute_repeats([(r[0], r[1]) for r in corpus()])
    assert substring_dedup.dedup(none).count() == 0
    out = substring_dedup.deduped(docs)
    assert out.columns == docs.columns and out.where("doc_id = 1").count() == 0 and out.where("doc_id = 0").first()["text"] == corpus()[0][1]


def test_substring_dedup_over_paths(spark):
    """Long copies, shared passages, passages of passages, circles and rows that share an id."""
    r = random.Random(13)
    make = lambda n, m=900: [f"t{r.randrange(m)}" for _ in range(n)]
    long_, passage, other = make(700), make(120), make(75)
    rows = [(1, make(30) + passage + make(40)), (2, long_), (3, make(10) + long_[100:600] + make(20)), (4, long_[:300] + make(5) + long_[305:]), (5, passage + other), (6, other + make(9) + passage[20:100])]
    rows += [(7, ["z"] * 200), (8, ["y", "z"] * 90), (9, make(60) + ["z"] * 130), (10, ["a", "b", "c"] * 60 + passage), (11, (["a", "b", "c"] * 60)[1:]), (1, other), (1, passage), (12, passage[:49]), (13, passage[:50])]
    rows += [(20 + i, make(r.randrange(30)) + long_[50 * i : 50 * i + 160] + make(r.randrange(30)) + passage[: 60 + i]) for i in range(10)]
    rows = [(d, " ".join(w)) for d, w in rows] + [(30, " ".join(long_)), (30, " ".join(long_))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = substring_dedup.dedup(df)
    assert sorted(map(tuple, got.drop("spans").collect()), key=str) == brute_repeats(rows)
    text = dict(reversed(rows))
    for x in got.where("spans is not null").collect():
        for s in x.spans:
            assert s.source < x.doc_id and any(d == s.source and " ".join(t.split()[s.there : s.there + s.words]) == " ".join(text[x.doc_id].split()[s.start : s.start + s.words]) for d, t in rows)
    assert max(s.words for x in got.where("doc_id in (3, 4)").collect() for s in x.spans) > 250


def brute_groups(rows, percent=80):
    def shingles(t):
        w = [x for x in words((t or "").translate({c: c + 32 for c in range(65, 91)}))]
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())

    sets = [(d, shingles(t)) for d, t in rows]
    label = {d: d for d, _ in sets}
    for (a, s), (b, u) in itertools.combinations([x for x in sets if x[0] is not None and x[1]], 2):
        if 100 * len(s & u) >= percent * len(s | u) and label[a] != label[b]:
            low, high = sorted((label[a], label[b]))
            label = {k: low if v == high else v for k, v in label.items()}
    return sorted(((d, len(s), label[d]) for d, s in sets), key=str)


def test_jaccard_join(docs, none):
    got = sorted(map(tuple, jaccard_join.join(docs).collect()), key=str)
    assert got == brute_groups([(r[0], r[1]) for r in corpus()])
    assert jaccard_join.join(none).count() == 0
    stay = jaccard_join.firsts(docs)
    assert stay.columns == docs.columns and {r["doc_id"] for r in stay.collect()} >= {0, 7, 8, 9, 10, None} and stay.where("doc_id in (1, 12)").count() == 0


def test_jaccard_join_with_a_large_region(spark):
    r = random.Random(1)
    base = ["b%d" % i for i in range(60)]
    rows = []
    for i in range(140):
        w = list(base)
        for _ in range(r.randrange(4)):
            w[r.randrange(60)] = "e%d" % r.randrange(30)
        rows.append((i, " ".join(w)))
    got = sorted(map(tuple, jaccard_join.join(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    assert got == sorted(brute_groups(rows))


def test_components(spark):
    r = random.Random(2)
    edges = [(r.randrange(90), r.randrange(90)) for _ in range(60)] + [(i, i + 1) for i in range(200, 260)]
    label = {v: v for e in edges for v in e}
    for a, b in edges:
        low, high = sorted((label[a], label[b]))
        label = {k: low if v == high else v for k, v in label.items()}
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert got == {k: v for k, v in label.items() if k in got} and {k for k, v in label.items() if list(label.values()).count(v) > 1} == set(got)


def test_embedding_dedup(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(60, 8))
    x[30:45] = x[:15] + 0.1 * rng.normal(size=(15, 8))
    rows = [(i, [float(v) for v in x[i]], i % 2 if i % 7 else None) for i in range(60)]
    rows += [(60, rows[1][1], 1), (61, rows[1][1], 1), (62, None, 1), (63, [], 1), (64, [0.0] * 8, 1), (65, [1.0, None], 1), (66, [float("nan")] * 8, 1), (67, [1.0] * 3, 1), (None, rows[1][1], 1), (61, rows[1][1], 1)]
    df = spark.createDataFrame([(*r, "c", 3) for r in rows], "vec_id long, embedding array<double>, label int, v string, n int")
    ok = [(i, np.array(v), la) for i, v, la in rows if i is not None and la is not None and v and None not in v and np.isfinite(v).all() and any(v)]
    cos = lambda a, b: a @ b / np.linalg.norm(a) / np.linalg.norm(b) if len(a) == len(b) else 0
    links = {k: [j for j, o in enumerate(ok) if j != k and o[2] == la and cos(v, o[1]) >= 0.93] for k, (i, v, la) in enumerate(ok)}
    label = {i: i for i, _, _ in ok}
    for k, js in links.items():
        for j in js:
            low, high = sorted((label[ok[k][0]], label[ok[j][0]]))
            label = {a: low if b == high else b for a, b in label.items()}
    want = sorted([(ok[k][0], len(js), label[ok[k][0]]) for k, js in links.items()])
    got = embedding_dedup.links(df).collect()
    assert len(got) == len(rows) and sorted((r.vec_id, r.n_links, r.component_id) for r in got if r.vec_id in label) == want
    assert all(r.n_links == 0 and r.kept for r in got if r.vec_id not in label)
    assert embedding_dedup.links(df.limit(0)).count() == 0


def test_embedding_dedup_over_several_shards(spark, monkeypatch):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(300, 16))
    x[100:200] = x[:100] + 0.05 * rng.normal(size=(100, 16))
    x[200:260] = x[0] + 0.02 * rng.normal(size=(60, 16))
    df = spark.createDataFrame([(i, [float(v) for v in x[i]], 0) for i in range(300)], "vec_id long, embedding array<double>, label int")
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = ((u @ u.T) >= 0.93).sum(1) - 1
    got = {r.vec_id: r.n_links for r in embedding_dedup.links(df, shard=80).collect()}
    assert sum(min(got[i], want[i]) for i in range(300)) >= 0.9 * want.sum() and all(got[i] <= want[i] for i in range(300))


def test_embedding_links_are_symmetric_over_shards_and_keys(spark, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "WIDEST", 60)
    rng = np.random.default_rng(5)
    x = rng.normal(size=(400, 12))
    x[100:180] = x[0] + 0.02 * rng.normal(size=(80, 12))
    x[200:300] = x[:100] + 0.2 * rng.normal(size=(100, 12))
    rows = [(i, [float(v) for v in x[i]], i % 3) for i in range(400)] + [(7, [float(v) for v in x[8]], 5), (9, [float(v) for v in x[8]], 5), (7, [float(v) for v in x[11]], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    u = np.array([v for _, v, _ in rows])
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    label = np.array([la for _, _, la in rows])
    link = ((u @ u.T) >= 0.93) & (label[:, None] == label[None, :])
    np.fill_diagonal(link, False)
    got = embedding_dedup.links(df, shard=40).collect()
    assert sum(r.n_links for r in got) % 2 == 0 and sorted((r.vec_id, r.n_links) for r in got) == sorted((rows[i][0], int(link[i].sum())) for i in range(len(rows)))
    seen = embedding_dedup.audits(df, shard=40).collect()
    assert seen and all(r.found_links >= 0.99 * r.true_links for r in seen) and sum(r.true_links for r in seen) > 100


def test_packing(docs, none):
    path = tokenizer_path("byte_bpe_50k.json")
    e = encoder(path)
    got = packing.pack(docs, path).collect()
    by = {}
    for r in got:
        by.setdefault(r.sequence_id, []).append(r)
    for v in by.values():
        at = 0
        for r in sorted(v, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
    want = []
    for r in corpus():
        ids = np.append(e.encode([r[1] or ""])[0], 1).astype("<u4")
        want += [(r[0], i, len(ids[i : i + 2048]), zlib.crc32(ids[i : i + 2048].tobytes()), len(ids)) for i in range(0, len(ids), 2048)]
    assert sorted([tuple(r)[:5] for r in got], key=str) == sorted(want, key=str)
    assert packing.pack(none, path).count() == 0


def test_token_store(spark, docs, none):
    from tokenizers import Tokenizer

    path, at = tokenizer_path("word_bpe_49k.json"), folder(spark)
    token_store.write(docs, at, path)
    library = Tokenizer.from_file(path)
    ids = {}
    for r in corpus():
        ids.setdefault(r[0], []).append(np.append(library.encode(r[1] or "", add_special_tokens=False).ids, 1).astype("<u4"))
    got = token_store.read(spark, at).collect()
    assert sorted([(r.doc_id, r.n_tokens, r.ids_crc32) for r in got], key=str) == sorted([(d, len(a), zlib.crc32(a.tobytes())) for d, v in ids.items() for a in v], key=str)
    end = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == end
        end += r.n_tokens
    order = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert order[:2] == [None, None] and order[2:] == sorted(order[2:])
    assert token_store.fetch(spark, at, 7).tolist() == ids[7][0].tolist() and token_store.fetch(spark, at, 999) is None
    token_store.write(none, at + "e", path)
    assert token_store.read(spark, at + "e").count() == 0


def test_warc(spark):
    odd = "x WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 5\r\n\r\nabcde\r\n\r\nWARC/1.1\r\ny"
    rows = [(1, "http://a", odd), (2, None, None), (3, "u\r\nX: y", "same"), (4, "u", "same"), (None, "u", "same"), (5, "u", "WARC/1.1\r\n"), (6, "u", "é\r\n\r\nWARC/1.1\r\n\r\n"), (7, "x", ""), (4, "u", "same"), (8, "u", "z" * 100_000 + odd)]
    df = spark.createDataFrame([(*r, "c") for r in rows], "page_id long, url string, html string, digest string")
    for parts in (1, 4):
        at = folder(spark)
        warc.write(df.repartition(parts), at)
        got = warc.read(spark, at).collect()
        assert len(got) == len(rows) and all(r.intact for r in got)
        last = {}
        for i, _, h in rows:
            if i is not None:
                last[h or ""] = max(i, last.get(h or "", i))
        import base64

        want = []
        for i, _, h in rows:
            b = (h or "").encode()
            revisit = i is not None and i < last[h or ""]
            want.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "revisit" if revisit else "response", last[h or ""] if revisit else None))
        assert sorted([(r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got], key=str) == sorted(want, key=str)
        assert {bytes(r.payload) for r in got if r.record_type == "response"} == {(h or "").encode() for _, _, h in rows}
    at = folder(spark)
    warc.write(df.limit(0), at)
    assert warc.read(spark, at).count() == 0


def test_torn_archive_keeps_only_what_the_start_reaches(spark):
    import pathlib

    record = lambda n: f"WARC/1.1\r\nWARC-Type: response\r\nPage-ID: {n}\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    at = pathlib.Path(re.sub("^file:/*", "/", folder(spark)))
    at.mkdir(parents=True)
    (at / "a.warc").write_bytes((record(1) + record(2) + "junk" + record(3)).encode())
    (at / "b.warc").write_bytes(("junk" + record(4)).encode())
    assert sorted(r.page_id for r in warc.read(spark, f"file://{at}").collect()) == [1]


def test_archives_are_followed_over_splits(spark):
    """Plain archives in many splits, with payloads that hold records and the ends of records, against a walk from the start."""
    r = random.Random(14)
    inner = lambda n: f"WARC/1.1\r\nPage-ID: {1000 + n}\r\nContent-Length: 4\r\n\r\nfake\r\n\r\n"
    rows = [(i, "u%d" % i, r.choice(["", "x" * r.randrange(3000), inner(i) * r.randrange(60), "é" * r.randrange(900) + "\r\n\r\n" + inner(i), "WARC/1.1\r\n" * r.randrange(5)]) + str(i)) for i in range(300)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    for size in (before, "2000", "700"):
        at = folder(spark)
        warc.write(df.coalesce(2), at, compression="none")
        spark.conf.set("spark.sql.files.maxPartitionBytes", size)
        try:
            got = {x.page_id: bytes(x.payload).decode() for x in warc.read(spark, at).collect()}
        finally:
            spark.conf.set("spark.sql.files.maxPartitionBytes", before)
        assert got == {i: h for i, _, h in rows}


def test_toxicity(spark, docs):
    r = random.Random(5)
    plain = ["tree", "house", "river", "you", "green", "walk", "stone", "cloud"]
    rows, labels = [], []
    for i in range(900):
        toxic = i % 4 == 0
        w = [r.choice(plain) for _ in range(30)]
        for _ in range(3 * toxic):
            w[r.randrange(30)] = r.choice(["idiot", "grobblat"])
        rows.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    df, la = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([*labels, (None, 1), (5, None)], "doc_id long, toxic int")
    got = toxicity.score(df, la, ["doc_id"]).collect()
    right = [(x.tox_score >= 0.7) == (x.doc_id % 4 == 0) for x in got if zlib.crc32(str(x.doc_id).encode()) % 3 == 1]
    assert len(right) > 200 and np.mean(right) > 0.97 and all(0 <= x.tox_score <= 1 for x in got)
    wide = toxicity.score(docs, la, ["doc_id", "key"])
    assert wide.count() == docs.count() and wide.where("tox_score is null").count() == 0
    assert toxicity.clean(docs, la.limit(0)).count() == docs.count() and toxicity.clean(docs.limit(0), la).count() == 0


def test_mixing(spark, docs, none):
    r = random.Random(6)
    rows = [(i, "w " * r.randrange(1, 40), ["a", "b", "c", None][min(3, int(r.expovariate(1)))]) for i in range(4000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.draws(df, shard_words=5000).collect()
    size = {}
    for _, t, s in rows:
        size[s] = size.get(s, 0) + len(words(t))
    goal = mixing.targets(size)
    taken = {}
    for x in got:
        assert x.mix_size == len(words(x.text)) and x.mix_source_size == size[x.source] and x.mix_target == goal[x.source] and len(x.mix_shards) <= 3
        taken[x.source] = taken.get(x.source, 0) + x.mix_size * len(x.mix_shards)
    assert all(abs(taken[s] - goal[s]) <= 40 for s in size)
    again = {x.doc_id: x.mix_shards for x in mixing.draws(df.repartition(5), shard_words=5000).collect()}
    assert again == {x.doc_id: x.mix_shards for x in got}
    assert mixing.mix(df).count() == sum(len(x.mix_shards) for x in got)
    mixed = [x.doc_id for x in mixing.mix(df).collect()]
    assert sum(a == b for a, b in zip(mixed, mixed[1:])) <= 0.02 * len(mixed) and max(mixed.count(i) for i in range(50)) > 1
    clash = mixing.mix(df.selectExpr("doc_id", "text", "source", "1 as mix_shard", "2 as mix_size", "3 as src"))
    assert clash.columns[3:] == ["mix_shard", "mix_size", "src"] and clash.count() == len(mixed)
    assert mixing.draws(docs).count() == docs.count() and mixing.draws(none).count() == 0 and mixing.mix(docs).columns == docs.columns


def test_quality(spark, docs, none):
    r = random.Random(8)
    rows = [(i, " ".join("w%d" % r.randrange(5000) for _ in range(r.randrange(60, 400))), "en", "s%d" % (i % 2)) for i in range(600)]
    bad = [(1000 + i, " ".join("w%d###" % r.randrange(5000) for _ in range(100)), "en", "s0") for i in range(10)]
    df = spark.createDataFrame(rows + bad, "doc_id long, text string, lang string, source string")
    got = {x.doc_id: x for x in quality.rules(df).collect()}
    assert all(not got[i].kept and not got[i].base_failed for i, *_ in bad) and sum(not got[i].kept for i, *_ in rows) <= 3
    few = quality.rules(docs).collect()
    assert len(few) == len(corpus()) and all(x.kept != x.base_failed for x in few)
    assert quality.rules(none).count() == 0


def test_quality_of_moderate_symbol_rates(spark):
    r = random.Random(9)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randrange(2, 10)))
    rows = [(i, " ".join(word() for _ in range(r.randrange(60, 400))), "en", "s0") for i in range(600)]
    pipes = [(1000 + i, " | ".join(word() for _ in range(r.randrange(60, 200))), "en", "s0") for i in range(15)]
    marked = [(2000 + i, " ".join(word() + "$" * (j % 5 == 0) for j in range(r.randrange(60, 200))), "en", "s0") for i in range(15)]
    got = {x.doc_id: x for x in quality.rules(spark.createDataFrame(rows + pipes + marked, "doc_id long, text string, lang string, source string")).collect()}
    assert all(not got[i].kept and not got[i].base_failed for i, *_ in pipes + marked) and sum(not got[i].kept for i, *_ in rows) <= 3


def test_quality_of_small_groups(spark):
    r = random.Random(10)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randrange(2, 10)))
    text = lambda: " ".join(word() for _ in range(r.randrange(60, 400)))
    junk = lambda: " ".join(word() + "$$$" for _ in range(100))
    rows = [(i, text(), "en", "s0") for i in range(300)] + [(300, text(), "en", "rare"), (301, text(), "es", "s0"), (302, text(), None, None)]
    bad = [(1000, junk(), "en", "rare"), (1001, junk(), "es", "s0"), (1002, junk(), None, None)]
    got = {x.doc_id: x for x in quality.rules(spark.createDataFrame(rows + bad, "doc_id long, text string, lang string, source string")).collect()}
    assert all(x.distance is not None for x in got.values())
    assert all(not got[i].kept and not got[i].base_failed for i, *_ in bad) and all(got[i].kept for i in (300, 301, 302))


def test_html_text(spark):
    page = lambda body: f"<html><head><title>t</title></head><body>{body}</body></html>"
    notice = "<div>this site is run by a club of friends since long ago</div>"
    rows = [(i, f"http://h.org/{i}", page(f"{notice}<p>page{i} has text of its own here</p>")) for i in range(5)]
    rows += [(9, "http://h.org/9", page("<article><p>a &lt; b</p>  <p>c\n d</p></article><footer>f</footer>")), (10, None, None), (11, "bad url", "plain"), (0, "http://h.org/0", rows[0][2]), (12, "http://other.org/", page(notice))]
    df = spark.createDataFrame([(*r, "c") for r in rows], "page_id long, url string, html string, host string")
    got = {r.page_id: r for r in html_text.extract(df).collect()}
    assert html_text.extract(df).count() == len(rows)
    assert [got[i].text for i in range(5)] == [f"page{i} has text of its own here" for i in range(5)]
    assert got[9].text == "a < b\nc d" and got[10].text == "" and got[11].text == "plain" and got[12].text.startswith("this site") and got[9].n_chars == 9
    assert html_text.extract(df.limit(0)).count() == 0


def test_html_repeats_against_brute_force(spark):
    """Pages without marks: menus and notices of a host go, copies of a page keep their text, whatever the tasks."""
    r = random.Random(16)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(4))
    text = lambda n: [" ".join(word() for _ in range(r.randrange(3, 30))) for _ in range(n)]
    rows, menus = [], {}
    for h in range(3):
        menu = ["M" + word() for _ in range(7)]
        notice = " ".join(word() for _ in range(14))
        menus[h] = menu
        pages_ = [text(r.randrange(1, 6)) for _ in range(12)]
        pages_[7] = pages_[3]  # a copy
        for i, blocks in enumerate(pages_):
            body = "<ul>" + "".join(f"<li>{m}</li>" for m in menu) + "</ul>" + "".join(f"<p>{b}</p>" for b in blocks) + f"<div>{notice}</div>"
            rows.append((100 * h + i, f"https://h{h}.org:80/p{i}", f"<body>{body}</body>"))
    rows.append(rows[3])
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = [{x.page_id: x.text for x in html_text.extract(df.repartition(n)).collect()} for n in (1, 5)]
    assert got[0] == got[1]
    streams = {(i, u): html_text.stream(html_text.blocks(h)) for i, u, h in rows}
    for i, u, h in rows:
        tokens, _ = streams[i, u]
        parts = html_text.blocks(h)
        found = []
        for at in range(len(tokens) - html_text.DEPTH + 1):
            piece = tokens[at : at + html_text.DEPTH]
            held = [x for x in rows if x[1].split("/")[2] == u.split("/")[2] and any(streams[x[:2]][0][k : k + html_text.DEPTH] == piece for k in range(len(streams[x[:2]][0])))]
            if len({x[:2] for x in held}) > 1:
                found.append((at, len(held)))
        assert got[0][i] == html_text.main_text(parts, found)
        assert not any(m in got[0][i].split() for m in menus[i // 100]) and got[0][i]
        if i % 100 not in (3, 7):
            assert got[0][i] == "\n".join(t for _, t in parts[7:-1])


def test_pipeline_stages_keep_the_columns(spark, docs, sf):
    from pointtree.llm.common import store

    d = docs
    for name, stage in corpus_pipeline.STAGES:
        d = store(stage(spark, d, sf), name)
        if name != "packing":
            assert d.columns == docs.columns
    assert d.where("doc_id = 7").count() > 0


def test_registry():
    q = registry.queries()
    assert [n.split("_")[0] for n in q] == [f"op{i}" for i in range(1, 11)] + ["pipeline"] and set(registry.oracle_sql()) <= set(q)
    assert F is not None


def test_jaccard_join_of_rows_that_share_an_id(spark):
    r = random.Random(11)
    make = lambda n: " ".join("v%d" % r.randrange(300) for _ in range(n))
    a, b = make(50), make(50)
    rows = [(1, a), (1, b), (2, a), (3, b + " more"), (4, make(40)), (4, make(40)), (5, a), (5, a)]
    df = spark.createDataFrame([(*x, "c") for x in rows], "doc_id long, text string, row string")
    got = sorted((x.doc_id, x.component_id) for x in jaccard_join.join(df).collect())
    assert got == [(1, 1), (1, 1), (2, 1), (3, 1), (4, 4), (4, 4), (5, 1), (5, 1)]
    stay = jaccard_join.firsts(df)
    assert stay.columns == df.columns and sorted((x.doc_id, x.text) for x in stay.collect()) == sorted([rows[0], rows[1], rows[4], rows[5]])


def test_jaccard_join_with_dealt_regions(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "CELL", 40)
    monkeypatch.setattr(jaccard_join, "STAR", 16)
    monkeypatch.setattr(jaccard_join.metric, "SMALL", 8)
    r = random.Random(12)
    base = ["b%d" % i for i in range(120)]
    rows = []
    for i in range(160):
        w = list(base)
        for _ in range(r.choice([0, 1, 4, 5])):
            w[r.randrange(120)] = "e%d" % r.randrange(3000)
        rows.append((i, " ".join(w[: r.choice([120, 110, 90])])))
    got = sorted(map(tuple, jaccard_join.join(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    assert got == sorted(brute_groups(rows))


def brute_verdicts(x, per_word, per_char, tenth):
    """Minimum covariance determinant of one group, all in memory."""
    at = lambda v, p: np.sort(v)[int(np.ceil(p * len(v))) - 1]
    floor = lambda on: np.array(quality._least(per_word[on].mean(), per_char[on].mean()))
    everything = np.ones(len(x), bool)
    middle = np.array([at(c, 0.5) for c in x.T])
    off = np.abs(x - middle)
    spread = lambda s: np.maximum(np.array(s) ** 2, floor(everything))
    absolute = [at(c, 0.5) / quality.DEVIATIONS for c in off.T]
    quartile = [(at(c, 0.75) - at(c, 0.25)) / quality.QUARTILES for c in x.T]
    starts = [(off**2 / spread(absolute)).sum(1), (off**2 / spread(quartile)).sum(1), np.zeros(len(x)), np.where(tenth, 0.0, np.nan)]

    def step(d):
        there = ~np.isnan(d)
        on = there & (d <= at(d[there], quality.KEPT_PART))
        mean, cov = x[on].mean(0), np.cov(x[on].T, bias=True)
        inverse, size = quality.estimate(mean, cov, floor(on))
        return size, mean, cov, floor(on), np.einsum("ni,ij,nj->n", x - mean, inverse, x - mean)

    fits = [step(d) for d in starts if not np.isnan(d).all()]
    fits = [step(f[4]) for f in fits]
    best = min(fits, key=lambda f: f[0])
    while (new := step(best[4]))[0] < best[0] - quality.FALL:
        best = new
    _, mean, cov, least, d = best
    inverse, _ = quality.estimate(mean, cov, least, at(d, 0.5))
    return np.einsum("ni,ij,nj->n", x - mean, inverse, x - mean)


def test_quality_against_brute_force(spark):
    r = random.Random(15)
    word = lambda: "".join(r.choice("abcdefghijklmn") for _ in range(r.randrange(2, 11)))
    rows = []
    for i in range(700):
        lang, source = ("en", "a") if i % 3 else ("de", None)
        w = [word() for _ in range(int(r.lognormvariate(5, 0.6)) + 25)]
        kind = r.random()
        if kind < 0.08:
            w = [x + r.choice("#*$") * r.randrange(3) for x in w]
        elif kind < 0.14:
            w = [x * 4 for x in w]
        text = " ".join(w)
        if 0.14 <= kind < 0.2:
            text += ("\n" + " ".join(w[:6])) * r.randrange(2, 9)
        rows.append((i, text, lang, source))
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = {x.doc_id: x for x in quality.rules(df).collect()}
    base = quality.base(df).withColumn("draw", F.pmod(F.xxhash64(*quality.X), F.lit(quality.TENTH))).collect()
    for group in ("en", "de"):
        of = [b for b in base if b.lang == group and not b.base_failed]
        x = np.array([[b[c] for c in quality.X] for b in of])
        d = brute_verdicts(x, np.array([b.per_word for b in of]), np.array([b.per_char for b in of]), np.array([b.draw == 0 for b in of]))
        assert np.allclose(d, [got[b.doc_id].distance for b in of], rtol=1e-6, atol=1e-9)
        assert [got[b.doc_id].kept for b in of] == (d <= quality.MOST_DISTANCE).tolist() and 0 < (d > quality.MOST_DISTANCE).sum() < len(of) / 3


def test_clashing_names_and_empty_tables(spark, sf, tmp_path):
    names = ["cut_id", "cut_text", "gone_id", "stay_id", "tox_score", "tox_text", "mix_shard", "mix_doc", "row", "root", "doc", "twice", "found", "copy", "kept_text", "label", "node"]
    r = random.Random(17)
    text = " ".join("w%d" % r.randrange(500) for _ in range(90))
    rows = [(0, text, "en", "a", len(text)), (1, text, "en", "a", len(text)), (2, "x y " + text, "de", None, None), (3, None, None, "b", None), (4, "", "en", "b", 0)]
    df = spark.createDataFrame([(*x, *["c"] * len(names)) for x in rows], "doc_id long, text string, lang string, source string, n_chars int, " + ", ".join(f"`{n}` string" for n in names))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, df, sf)
        assert out.columns == df.columns and out.select("doc_id", "root", "mix_doc").count() >= 3, name
    assert substring_dedup.deduped(df).where("doc_id = 2").first()["text"] == "x y"
    for t in ("documents", "labels"):
        spark.read.parquet(f"{sf}/{t}.parquet").limit(0).write.parquet(f"file://{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0


def test_very_long_texts(spark):
    """One text of 400,000 words beside short ones, through what reads whole texts."""
    long_ = " ".join(f"q{i * 7919 % 30011}" for i in range(400_000))
    passage = " ".join(f"p{i}" for i in range(70))
    rows = [(0, long_, "en", "a"), (1, long_ + " tail", "en", "a"), (2, passage, "en", "b"), (3, long_[:100_000] + " " + passage, "en", "b")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = {x.doc_id: x for x in jaccard_join.join(df).collect()}
    assert got[1].component_id == 0 and got[3].component_id == 3
    cut = {x.doc_id: x.n_removed for x in substring_dedup.dedup(df).collect()}
    assert cut[0] == 0 and cut[1] >= 400_000 and cut[3] >= 14_000
    assert {x.doc_id: x.n_words for x in quality.rules(df).collect()}[0] == 400_000
    path = tokenizer_path("word_bpe_49k.json")
    at = folder(spark)
    token_store.write(df, at, path)
    assert token_store.read(spark, at).where("doc_id = 1").first()["n_tokens"] > 400_000
    assert packing.pack(df.where("doc_id < 2")).agg(F.sum("length")).first()[0] > 800_000
    assert mixing.draws(df).where("doc_id = 0").first()["mix_size"] == 400_000
