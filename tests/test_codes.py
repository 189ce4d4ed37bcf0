"""Bit vectors, variable-length codes and packed trees, against plain arrays."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pointtree.config import TreeConfig, sides
from pointtree.functions.mlv import Mlv, encode, unzigzag, zigzag
from pointtree.functions.succinct import BitVec, leaf_range, tally
from pointtree.operators import shards


def text(v: BitVec) -> str:
    return "".join(map(str, v.bits()))


@settings(max_examples=60, deadline=None)
@given(st.lists(st.booleans(), max_size=400))
def test_rank_and_select(bits):
    b = np.array(bits, np.uint8)
    v = BitVec.from_bytes(BitVec.from_bits(b).to_bytes())
    n = len(b)
    assert (v.rank1(np.arange(n + 1)) == np.concatenate([[0], np.cumsum(b)])).all()
    ones, zeros = np.flatnonzero(b), np.flatnonzero(b == 0)
    assert (v.select1(np.arange(len(ones))) == ones).all() and (v.select0(np.arange(len(zeros))) == zeros).all()
    assert (v.rank1(v.select1(np.arange(len(ones)))) == np.arange(len(ones))).all()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**61)), st.sampled_from(["auto", [4], [3, 7, 2]]))
def test_codes_give_back_every_value(values, widths):
    m = Mlv.from_bytes(encode(values, widths).to_bytes())
    assert m.slice(0, len(values)).tolist() == values
    assert m.get(range(len(values))[::-1]).tolist() == values[::-1]


def test_best_widths_are_no_worse_than_fixed_ones():
    v = np.random.default_rng(1).exponential(900, 3000).astype(np.uint64)
    assert encode(v).bits <= min(encode(v, [w]).bits for w in range(1, 14))


def test_signs_and_missing_values():
    v = np.array([-24, 28, 0, 3])
    assert (unzigzag(zigzag(v)) == v).all()
    f = np.array([1, np.nan, -5, np.nan, 7])
    c = shards.Column.from_bytes(shards.Column.encode(f).to_bytes())
    np.testing.assert_array_equal(c.get(np.arange(5)), f)
    assert shards.Column.encode(np.array([0, 1, 1])).kind == "bit"


def test_unary_counts():
    t = tally(np.array([3, 1, 2]))
    assert text(t) == "001101"
    assert [a.tolist() for a in leaf_range(t, np.arange(3))] == [[0, 3, 4], [3, 4, 6]]


EX1 = np.array([(0, 0, 0), (1, 1, 0), (3, 0, 2), (3, 3, 3), (5, 0, 0), (4, 2, 1), (6, 1, 3), (7, 7, 7)])
PID = np.arange(1, 9)


def test_hand_made_tree():
    t = shards.pack(*EX1.T, PID, {"intensity": PID * 10}, (2, 2, 2), 3)
    assert text(t.branch) == "1" + "0" * 15 and text(t.occupied) == "000100110000101" and text(t.tally) == "00110111"
    assert PID[t.permutation].tolist() == [5, 6, 7, 8, 1, 2, 3, 4]
    assert [c.slice(0, 8).tolist() for c in t.coordinates] == [[1, 0, 2, 3, 0, 1, 1, 1], [0, 2, 1, 3, 0, 1, 0, 1], [0, 1, 3, 3, 0, 0, 0, 1]]
    assert t.attributes["intensity"].get(np.arange(8)).tolist() == [50, 60, 70, 80, 10, 20, 30, 40]
    lex = shards.pack(*EX1.T, PID, {}, (2, 2, 2), 3, "lex")
    assert PID[lex.permutation].tolist()[:3] == [6, 5, 7]


def test_early_stop_on_interleaved_order_loses_nothing():
    t = shards.pack(*EX1.T, PID, {}, (2, 2, 2), 3)
    assert PID[t.permutation[shards.scan(t, (4, 0, 0, 4, 3, 3))["_position"]]].tolist() == [6]
    assert sorted(PID[t.permutation[shards.scan(t, (4, 0, 0, 5, 2, 1))["_position"]]]) == [5, 6]


def test_last_level_holds_any_number():
    p = np.array([(0, 0, 0)] * 4 + [(0, 0, 1), (3, 3, 3)])
    t = shards.pack(*p.T, np.arange(6), {"a": np.arange(6)}, (2, 2), 3)
    assert (text(t.branch), text(t.occupied), text(t.tally)) == ("10000000", "000000111000000", "100011")
    assert t.stored == 1 and t.attributes["a"].body.n == 6
    assert len(shards.scan(t, (0, 0, 0, 0, 0, 0))["x"]) == 4


@pytest.mark.parametrize("schedule", [(2, 2, 2, 2), (4, 2, 2), (4, 4), (2, 4, 2), (2,), (4,)])
@pytest.mark.parametrize("order", ["zorder", "lex"])
def test_random_boxes(schedule, order):
    r = np.random.default_rng(len(schedule))
    side = int(np.prod(schedule))
    for case in range(8):
        m = int(r.integers(0, 300))
        p = r.integers(0, side, (m, 3)) if case % 2 else np.minimum(side - 1, r.exponential(side / 6, (m, 3)).astype(int))
        a = r.integers(0, 90, m).astype(float)
        if case % 3 == 0:
            a[r.random(m) < 0.3] = np.nan
        t = shards.from_row(shards.to_row(shards.pack(*p.T, np.arange(m), {"a": a}, schedule, int(r.integers(1, 12)), order, case == 7)))
        # invariants: one flag per undivided box, one count per occupied one, coordinates are a prefix
        if not t.root_leaf:
            assert t.occupied.ones == t.tally.ones and t.tally.n == m and t.branch.n % schedule[0] ** 3 == 0 or len(set(schedule)) > 1
        for _ in range(5):
            lo = r.integers(0, side, 3)
            hi = np.minimum(side - 1, lo + r.integers(0, side, 3))
            want = p[((p >= lo) & (p <= hi)).all(1)]
            for stop in ("auto", "none", "x", "code"):
                g = shards.scan(t, (*lo, *hi), stop=stop)
                assert sorted(zip(g["x"], g["y"], g["z"], strict=True)) == sorted(map(tuple, want))
            got = shards.scan(t, (*lo, *hi), [("a", 10, 40)], ["a"])
            assert len(got["a"]) == (((p >= lo) & (p <= hi)).all(1) & (a >= 10) & (a <= 40)).sum()
        full = shards.scan(t, (0, 0, 0, side - 1, side - 1, side - 1))
        for k in range(0, m, 17):
            at = np.flatnonzero(full["_position"] == k)[0]
            q = shards.point_at(t, k)
            assert (q["x"], q["y"], q["z"]) == (full["x"][at], full["y"][at], full["z"][at])


def test_parameters():
    assert TreeConfig().parts(7) == (2, 2, 2) and TreeConfig().parts(8) == (2,) * 4 and TreeConfig(schedule=(4, 2)).parts(15) == (4, 2, 2)
    assert TreeConfig().parts(0) == (2,) and sides((4, 2)) == [8, 2, 1]
    with pytest.raises(ValueError):
        TreeConfig(fanout=3)


def test_entry_imports_without_a_session():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parents[1]
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()) >= len(e.oracle_sql()) > 100)"], cwd=root, capture_output=True, text=True, timeout=120)
    assert out.stdout.strip().endswith("True"), out.stderr[-2000:]
