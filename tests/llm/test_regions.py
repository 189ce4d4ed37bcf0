"""The metric join inside a region against brute force."""

import numpy as np

from pointtree.llm import regions


def family(rng, bases, copies, size, most):
    out = []
    for _ in range(bases):
        base = rng.integers(0, 1 << 63, size).astype(np.uint64)
        for _ in range(copies):
            s = base.copy()
            n = rng.integers(0, most)
            s[rng.integers(0, size, n)] = rng.integers(0, 1 << 63, n).astype(np.uint64)
            out.append(np.unique(s[: rng.integers(size // 2, size + 1)]))
    return out


def jaccard(a, b):
    both = len(np.intersect1d(a, b))
    return 100 * both >= 80 * (len(a) + len(b) - both)


def parts(n, edges):
    return regions.roots(n, np.array([a for a, _ in edges], np.int64), np.array([b for _, b in edges], np.int64))


def test_sketches_never_exceed_the_symmetric_difference():
    rng = np.random.default_rng(1)
    for a in family(rng, 3, 4, 700, 200):
        for b in family(rng, 1, 2, 900, 10):
            bits = min(regions.width(len(a)), regions.width(len(b)))
            x, y = (regions.parity(s, regions.width(len(s))) for s in (a, b))
            x, y = (s if 8 * len(s) == bits else regions.fold(s) for s in (x, y)) if max(len(x), len(y)) * 8 <= 2 * bits else (regions.parity(a, bits), regions.parity(b, bits))
            assert sum((p ^ q).bit_count() for p, q in zip(x, y)) <= len(np.setxor1d(a, b))


def test_candidates_hold_every_link_and_links_join_what_links_join():
    rng = np.random.default_rng(2)
    for bases, copies, size, most in ((1, 9, 40, 8), (5, 60, 120, 30), (40, 5, 400, 60), (1, 250, 300, 70)):
        sets = family(rng, bases, copies, size, most)
        n = len(sets)
        sizes, sketches = np.array([len(s) for s in sets]), [regions.parity(s, regions.width(len(s))) for s in sets]
        true = {(i, j) for j in range(n) for i in range(j) if jaccard(sets[i], sets[j])}
        i, j = regions.candidates(sizes, sketches, np.arange(n), 80)
        assert true <= set(zip(i.tolist(), j.tolist()))
        found = regions.links(np.arange(n), np.arange(n), sets, 80)
        assert {(min(e), max(e)) for e in found} <= true
        assert parts(n, found).tolist() == parts(n, sorted(true)).tolist()
        for _, members in regions.clusters(np.arange(n), sizes, sketches, np.arange(n), 80):
            assert len(members) > 1


def test_sets_of_one_label_are_not_compared():
    rng = np.random.default_rng(3)
    sets = family(rng, 1, 30, 200, 5)
    assert regions.links(np.arange(30), np.zeros(30, np.int64), sets, 80) == []
    label = np.zeros(30, np.int64)
    label[7] = 1
    assert len(regions.links(np.arange(30), label, sets, 80)) <= 29
