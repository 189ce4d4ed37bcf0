"""The operators' plain parts, without Spark."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pointtree.llm import html_text, mixing, packing, quality, substring_dedup, toxicity
from pointtree.llm.boosting import Boosted, Isotonic
from pointtree.llm.common import rolling, sliding_min, word_hashes
from pointtree.llm.encoding import encoder, tokenizer_path
from pointtree.llm.small_world import SmallWorld
from pointtree.llm.token_store import Frames


@settings(max_examples=100, deadline=None)
@given(st.lists(st.sampled_from([b"a", b"b", b"c"]), max_size=60), st.integers(1, 7))
def test_rolling_hashes_tell_runs_apart(words, k):
    h = rolling(word_hashes(words), k)
    runs = [tuple(words[i : i + k]) for i in range(len(words) - k + 1)]
    assert len(h) == len(runs)
    for i in range(len(runs)):
        for j in range(i):
            assert (h[i] == h[j]) == (runs[i] == runs[j])


def test_sliding_min():
    v = np.random.default_rng(1).integers(0, 99, 50).astype(np.uint64)
    for w in (1, 2, 3, 5, 8, 35):
        assert sliding_min(v, w).tolist() == [min(v[i : i + w]) for i in range(len(v) - w + 1)]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_ids_are_the_librarys(name):
    e = encoder(tokenizer_path(name))
    r = random.Random(3)
    texts = ["", " ", "  a  b ", "a\n b", "\xa0 x \xa0y", "It's  we're　 ok '", "A <|endoftext|> b", "x\x85 y", "İstanbul é é", "ǅ ﬁ 12 345", "a​ b", "don't stop,", "日本語 text", "ß SS ẞ"]
    texts += ["".join(r.choice("ab '1.\n\t \xa0é́ !") for _ in range(40)) for _ in range(400)]
    for t, ids in zip(texts, e.encode(texts), strict=True):
        assert ids.tolist() == e.tokenizer.encode(t, add_special_tokens=False).ids, repr(t)


def test_words_of_one_spelling_are_encoded_once():
    e = encoder(tokenizer_path("word_bpe_49k.json"))
    e.word.drop(), e.piece.drop()
    asked, tokenize = [], e.tokenize
    e.tokenize = lambda raw: asked.append(raw) or tokenize(raw)
    try:
        text = "Zqvxing, zqvxing\nZQVXING. zqvxing  É zqvxing;\n\né"
        ids = e.encode([text])[0].tolist()
    finally:
        e.tokenize = tokenize
    assert ids == e.tokenizer.encode(text, add_special_tokens=False).ids
    assert len(asked) == len(set(asked)) and asked.count("zqvxing") == 1


def best_fit(lengths, window):
    room, out = [], []
    for n in sorted(lengths, reverse=True):
        fits = [i for i, r in enumerate(room) if r >= n]
        i = min(fits, key=lambda i: room[i]) if fits else len(room)
        if not fits:
            room.append(window)
        room[i] -= n
        out.append((n, i))
    return room


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 32), max_size=150))
def test_plan_is_best_fit_decreasing(lengths):
    histogram = {n: lengths.count(n) for n in set(lengths)}
    placed, opened = packing.plan(histogram, 32)
    fill = {}
    for p in placed:
        for r in range(p.first_rank, p.first_rank + p.count):
            i = r - p.first_rank
            fill.setdefault(p.first_window + i // p.each, []).append((p.offset + i % p.each * p.length, p.length))
    assert sorted(n for v in fill.values() for _, n in v) == sorted(lengths)
    for v in fill.values():
        at = 0
        for offset, n in sorted(v):
            assert offset == at
            at += n
        assert at <= 32
    assert sorted(32 - sum(n for _, n in v) for v in fill.values()) == sorted(best_fit(lengths, 32)) and opened == len(fill)


def test_frames_round_trip():
    f = Frames(b"")
    for ids in ([1], [70_000, 3], list(range(5000))):
        a = np.array(ids, np.uint32)
        assert zlib.crc32(f.unpack(f.pack(a)).tobytes()) == zlib.crc32(a.astype("<u4").tobytes())


def test_targets_share_again_what_is_over():
    t = mixing.targets({"a": 10, "b": 1000, None: 10, "c": 0})
    assert t["c"] == 0 and t["a"] == 30 or t["a"] <= 30
    assert abs(sum(t.values()) - 1020) < 1e-6 and all(t[s] <= 3 * n + 1e-9 for s, n in {"a": 10, "b": 1000, None: 10, "c": 0}.items())
    assert mixing.targets({}) == {}


def test_splitting_tree_deals_every_rank_once_and_evenly():
    quotas, shards = [40, 7, 0, 113], 5
    tree = mixing.SplittingTree(quotas, shards, 3)
    got = {}
    for s, n in enumerate(quotas):
        for r in range(n):
            got.setdefault(tree.shard(s, r), []).append((s, r))
    assert sum(map(len, got.values())) == 160 and max(map(len, got.values())) - min(map(len, got.values())) <= 3
    assert [mixing.SplittingTree(quotas, shards, 3).shard(3, r) for r in range(113)] == [tree.shard(3, r) for r in range(113)]


def brute_statistics(text):
    words = [w for w in __import__("re").findall(r"[^\x20\x09-\x0D]+", text)]
    seen, dup = set(), 0
    for line in text.split("\n"):
        if line in seen and line.strip(" \t\n\x0b\x0c\r"):
            dup += 1
        seen.add(line)
    runs = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    covered = {i + k for i, r in enumerate(runs) if runs.count(r) > 1 for k in range(8)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(covered)


@settings(max_examples=80, deadline=None)
@given(st.text(alphabet="ab é　#|\n\t", max_size=200))
def test_statistics(text):
    assert quality.statistics(text.encode()) == brute_statistics(text)


def test_spans_join_at_one_distance_from_one_source():
    found = [(0, 3, 50, 1, 9, 20), (0, 4, 50, 1, 9, 21), (0, 5, 50, 1, 9, 22), (0, 6, 50, 1, 9, 40), (0, 90, 50, 2, 8, 0), (0, 56, 50, 1, 9, 73), (1, 4, 50, 1, 9, 21), (1, 54, 60, 1, 9, 71), (1, 60, 10, 1, 9, 77)]
    got = list(zip(*[c.tolist() for c in substring_dedup.spans(*np.array(found).T)], strict=True))
    assert sorted(got) == [(0, 3, 52, 1, 9, 20), (0, 6, 50, 1, 9, 40), (0, 56, 50, 1, 9, 73), (0, 90, 50, 2, 8, 0), (1, 4, 110, 1, 9, 21)]


def test_nodes_and_stretches_of_equal_words_are_equal():
    rng = np.random.default_rng(4)
    run = rng.integers(0, 1 << 62, 300).astype(np.uint64)
    texts = [np.concatenate([rng.integers(0, 1 << 62, n).astype(np.uint64), run, rng.integers(0, 1 << 62, n).astype(np.uint64)]) for n in (7, 40)]
    known = np.intersect1d(*[sliding_min(rolling(h, 16), 35) for h in texts])
    (p, a, s, d), (q, b, t, e) = (substring_dedup.nodes(h, known, 50, 16) for h in texts)
    assert len(p) > 8 and (q - p == 33).all() and (a == b).all() and (s == t).all() and (d == e).all()
    assert (s[:-1] != 0).all() and s[-1] == 0 and (d[:-1] == np.diff(p)).all()


def test_trees_and_calibration():
    r = np.random.default_rng(1)
    x = r.random((3000, 5))
    y = ((x[:, 0] > 0.6) & (x[:, 3] < 0.5)).astype(float)
    b = Boosted(trees=40).fit(x, y)
    assert ((b.raw(x) > 0) == y).mean() > 0.98
    i = Isotonic().fit(np.array([0.1, 0.4, 0.3, 0.9]), np.array([0.0, 1, 0, 1]))
    assert (np.diff(i(np.linspace(0, 1, 50))) >= 0).all()
    assert Boosted().fit(np.zeros((0, 5)), np.zeros(0)).raw(x[:2]).shape == (2,)


def test_toxic_features():
    c = toxicity.Classes(frozenset())
    f = toxicity.features(b"You are an IDIOT, you m0ron!", c)
    assert f[0] == 1 / 6 and f[4] == 1 / 6 and f[6] > 0
    assert not toxicity.features(None, c).any() and not toxicity.features(b" \n", c).any()


PAGE = """<!doctype html><html><head><title>T</title><style>p{}</style></head><body><nav><ul><li>Home<li>About</ul></nav>
<div class="ad big">Buy</div><p>Hosted by us all the time</p><main><h1>A &amp; B</h1><p>one  <b>two</b><br>three</p><script>if (a < b) "</main>"</script><div class=comments><p>first!</p></div>
<ul><li>x<li>y</ul></main><aside>more</aside><footer>&copy; z</footer></body>"""


def test_blocks_of_a_page():
    got = html_text.blocks(PAGE)
    assert [t for r, t in got if r == 0] == ["A & B", "one two three", "x", "y"]
    assert [t for r, t in got if r == 1] == ["Hosted by us all the time"]
    assert html_text.blocks(None) == [] and html_text.blocks("<p") == [(1, "<p")]
    assert [t for _, t in html_text.blocks("<nav>menu<article><p>text</article>") if _ == 0] == ["text"]


def test_suffix_intervals():
    a, b = list(range(20)), [50, 51, *range(3, 15), 60]
    order, starts, owner = html_text.suffix_intervals([a, b])
    stops = [*starts[1:], len(order)]
    repeated = [s for s, e in zip(starts, stops, strict=True) if len(set(owner[s:e])) > 1]
    assert len(repeated) == 12 - html_text.DEPTH + 1
    assert html_text.suffix_intervals([[], [1]])[0].size == 0


def test_small_world_finds_near_vectors():
    r = np.random.default_rng(5)
    x = r.normal(size=(1500, 32))
    x[700:900] = x[:200] + 0.05 * r.normal(size=(200, 32))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g = SmallWorld.from_bytes(SmallWorld(x).to_bytes(), x)
    ids, _ = g.search(x[:200], 16)
    assert np.mean([700 + i in ids[i] for i in range(200)]) > 0.97
    assert SmallWorld(x[:1]).search(x[:1], 4)[0].max() == 0
    assert hashlib.sha256(SmallWorld(x).to_bytes()).digest() is not None
