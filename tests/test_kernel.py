"""The window stack's kernel against worked examples, brute force and invariants."""

import random

import numpy as np
import pytest

from hybridrange.baselines.kernels import KINDS, IntervalGraph
from hybridrange.kernel.ordertree import SortedArray, WeightBalancedTree
from hybridrange.kernel.stack import Settings, Stack, diverse, far
from hybridrange.layers import landing_layer, top_layer

WORKED = [10, 35, 48, 55, 60, 72, 74, 81, 98, 99]


def data(n=300, d=16, values=None, seed=1):
    r = np.random.default_rng(seed)
    v = r.normal(size=(n, d))
    codes = r.permutation(n) if values is None else r.integers(0, values, n)
    return v / np.linalg.norm(v, axis=1)[:, None], codes


def truth(v, codes, q, bounds, k):
    rows = np.flatnonzero((codes >= bounds[0]) & (codes <= bounds[1]))
    return rows[np.argsort(far(v, rows, q), kind="stable")][:k].tolist() if len(rows) else []


@pytest.mark.parametrize("kind", [SortedArray, WeightBalancedTree])
def test_order_statistics(kind):
    r, tree, seen = random.Random(4), kind(), set()
    for _ in range(600):
        x = r.randrange(300)
        assert tree.insert(x) == (x not in seen)
        seen.add(x)
    ordered = sorted(seen)
    assert len(tree) == len(ordered)
    for i, x in enumerate(ordered):
        assert tree.select(i) == x and tree.rank(x) == i
    for _ in range(200):
        a, b = r.randrange(-5, 310), r.randrange(-5, 310)
        assert tree.count(a, b) == sum(a <= x <= b for x in ordered)
    if kind is WeightBalancedTree:
        assert tree.balanced()


def test_sorted_input_keeps_the_tree_balanced():
    tree = WeightBalancedTree()
    for i in range(2000):
        tree.insert(i)
    assert tree.balanced()


def test_worked_windows():
    s = Stack(np.zeros((11, 2)), np.array([*WORKED, 73]), Settings(o=4))
    for x in WORKED:
        s.values.insert(x)
    assert top_layer(10, 4) == 2
    assert s.window(74, 1) == (48, 99) and s.window(74, 0) == (72, 81)
    assert s.window(98, 1)[0] == 60
    s.values.insert(73)
    assert s.window(98, 1)[0] > 60


def test_layers():
    assert [top_layer(n, 4) + 1 for n in (1_000_000, 1_000_000, 2_138_591, 4_000_000, 10_000_000)] == [11, 11, 12, 12, 13]
    assert landing_layer(2048, 2, 20) == 10 and landing_layer(62_500, 4, 10) == 7
    assert landing_layer(0, 4, 5) is None and landing_layer(1, 4, 5) == 0 and landing_layer(10**9, 4, 3) == 3


def test_longest_side_is_pruned():
    v = np.array([[0.0, 0], [1, 0], [2, 0.5]])
    d = far(v, [1, 2], v[0]).tolist()
    assert diverse(v, d, [1, 2], 8) == [1]


@pytest.mark.parametrize("more", [{}, {"carry_over": False}, {"lazy": False}, {"tree": True}, {"o": 2}, {"strict": True}])
def test_recall_and_invariants(more):
    v, codes = data()
    s = Stack(v, codes, Settings(**more)).build()
    for layer in s.links:
        for i, mine in enumerate(layer):
            assert len(mine) <= s.s.m and i not in mine and len(set(mine)) == len(mine)
    hits = want = 0
    for i in range(0, 300, 7):
        w = [1, 5, 40, 150, 300][i % 5]
        a = i * 31 % (301 - w)
        f = s.query(v[i], (a, a + w - 1), 10, 64)
        t = truth(v, codes, v[i], (a, a + w - 1), 10)
        assert all(a <= codes[r] < a + w for r in f.rows) and len(f.rows) == len(t) and f.dist == sorted(f.dist)
        hits += len(set(f.rows) & set(t))
        want += len(t)
    assert hits / want >= (0.85 if more.get("strict") else 0.95)  # the literal window leaves layer 0 without links


def test_wide_beam_is_nearly_exact():
    v, codes = data()
    s = Stack(v, codes).build()
    got = [len(set(s.query(v[i], (50, 250), 10, 300).rows) & set(truth(v, codes, v[i], (50, 250), 10))) for i in range(0, 300, 10)]
    assert np.mean(got) >= 9.9


def test_duplicates_lower_the_layers():
    v, codes = data(values=10)
    s = Stack(v, codes).build()
    assert len(s.links) == top_layer(10, 4) + 1 == 3
    assert len(s.query(v[0], (3, 3), 5, 64).rows) == min(5, int((codes == 3).sum()))


def test_edges_of_ranges():
    v, codes = data(50)
    s = Stack(v, codes).build()
    assert s.query(v[0], (30, 20)).rows == [] and s.query(v[0], (100, 200)).rows == []
    assert len(s.query(v[0], (-5, 500)).rows) == 10 and len(s.query(v[0], (7, 7)).rows) == 1
    assert Stack(v[:1], codes[:1]).build().query(v[0], (-9, 99)).rows == [0]
    assert len(Stack(np.ones((20, 4)), np.arange(20)).build().query(np.ones(4), (0, 19), 10, 64).rows) == 10


def test_marked_rows_are_walked_and_not_returned():
    v, codes = data()
    s = Stack(v, codes).build()
    first = s.query(v[5], (0, 299)).rows[0]
    s.deleted[first] = True
    again = s.query(v[5], (0, 299))
    assert first not in again.rows and len(again.rows) == 10


def test_early_stop_saves():
    v, codes = data(600)
    s = Stack(v, codes).build()
    on = [s.query(v[i], (100, 400), 10, 32) for i in range(0, 600, 20)]
    off = [s.query(v[i], (100, 400), 10, 32, early_stop=False) for i in range(0, 600, 20)]
    assert np.mean([f.dc for f in on]) <= np.mean([f.dc for f in off]) and np.mean([f.fc for f in on]) <= np.mean([f.fc for f in off])


@pytest.mark.parametrize("kind", sorted(KINDS))
def test_baselines_stay_in_range(kind):
    v, codes = data(200)
    order = np.argsort(codes) if kind == "interval_graph" else np.arange(200)
    held = KINDS[kind](v[order], codes[order])
    hits = want = 0
    for i in range(0, 200, 9):
        a, w = i * 7 % 150, 50
        f = held.query(v[i], (a, a + w - 1), 10, 64)
        assert all(a <= held.codes[r] < a + w for r in f.rows) and len(set(f.rows)) == len(f.rows) <= 10
        t = truth(held.vecs, held.codes, v[i], (a, a + w - 1), 10)
        hits, want = hits + len(set(f.rows) & set(t)), want + len(t)
    assert hits / want >= 0.4


def test_tree_takes_insertions_and_splits():
    v, codes = data(400)
    tree = KINDS["multiway_tree"](v, codes, first=0.2, least=20, fanout=4)

    def below(node):
        return [y for x in node.children for y in below(x)] if node.children else [node]

    def depth(node):
        return 1 + max(map(depth, node.children), default=0)

    leaves = below(tree.root)
    assert sorted(r for x in leaves for r in x.rows) == list(range(400)) and len(leaves) > 8 and depth(tree.root) >= 3
    assert all(a.high <= b.low for a, b in zip(leaves, leaves[1:], strict=False)) and all(len(x.rows) < 2 * 20 for x in leaves)
    f = tree.query(v[3], (50, 249), 10, 64)
    assert len(set(f.rows) & set(truth(v, codes, v[3], (50, 249), 10))) >= 8


def test_the_published_method_alone_may_return_fewer_rows():
    v, codes = data(300)
    s = Stack(v, codes, Settings(m=4, omega_c=8)).build()
    both = [(s.query(v[i], (i, i + 12), 10, 10, complete=c)) for i in range(0, 250, 10) for c in (False, True)]
    assert all(len(b.rows) == 10 for b in both[1::2]) and all(not a.scanned and len(a.rows) <= 10 for a in both[::2])
    few = s.query(v[0], (0, 299), 10, 64, budget=2)
    assert few.dc <= s.query(v[0], (0, 299), 10, 64).dc and s.query(v[0], (0, 299), 10, 64, landing="estimate").rows


def test_interval_graph_needs_order():
    v, codes = data(20)
    with pytest.raises(ValueError):
        IntervalGraph(v, codes)
