"""A query's distances in a segment are taken at once, segments are dealt to many tasks, and small flat graphs are built from them."""

import numpy as np

from hybridrange import index
from hybridrange.baselines.kernels import BlockSuperset, OracleGraph
from hybridrange.kernel import stack
from hybridrange.kernel.stack import Settings, Stack


def data(n=300, dims=8, seed=4):
    rng = np.random.default_rng(seed)
    return rng.normal(size=(n, dims)), rng.permutation(n)


def test_a_query_takes_its_distances_once_with_the_same_results(monkeypatch):
    vecs, codes = data()
    held = Stack(vecs, codes).build()
    held.deleted[::7] = True
    asked = [(i, bounds, how) for i in (0, 5, 9) for bounds in ((0, 299), (40, 90), (7, 7)) for how in ({}, {"early_stop": False, "landing": "top"}, {"budget": 3, "complete": False})]
    told = lambda: [(f.rows, f.dist, f.dc, f.fc, f.in_range) for i, b, how in asked for f in [held.query(vecs[i], b, 10, 32, **how)]]
    calls, plain = [], stack.far
    monkeypatch.setattr(stack, "far", lambda *a: calls.append(1) or plain(*a))
    once = told()
    n = len(calls)
    monkeypatch.setattr(stack, "AT_ONCE_QUERY", 0)
    assert told() == once and n <= 2 * len(asked) < (len(calls) - n) / 3


def test_segments_are_dealt_to_more_tasks_than_a_shuffle_has(spark):
    rows = spark.range(2100).selectExpr("floor(id / 100) seg", "0 sub", "id")
    sizes = [len({r.seg for r in part}) for part in index.dealt(rows, "seg", "sub").rdd.glom().collect()]
    assert sum(sizes) == 21 and max(sizes) <= 3


def test_a_wide_shuffle_gets_no_more_tasks_for_segments(spark):
    rows, n = spark.range(100).selectExpr("id seg", "0 sub"), spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "211")
    try:
        assert index.dealt(rows, "seg", "sub").rdd.getNumPartitions() == 211
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", n)


def searched(monkeypatch, make):
    beams, plain = [], Stack.beam
    monkeypatch.setattr(Stack, "beam", lambda self, *a, **k: beams.append(1) or plain(self, *a, **k))
    made = make()
    monkeypatch.setattr(Stack, "beam", plain)
    return made, len(beams)


def near(vecs, codes, q, low, high, k=10):
    rows = np.flatnonzero((codes >= low) & (codes <= high))
    return set(rows[np.argsort(stack.far(vecs, rows, q))[:k]].tolist())


def hits(held, vecs, codes):
    return np.mean([len(near(vecs, codes, vecs[i], 30, 200) & set(held.query(vecs[i], (30, 200), 10, 64).rows)) / 10 for i in range(20)])


def test_the_graph_of_a_range_is_built_without_searches(monkeypatch):
    vecs, codes = data()
    held, beams = searched(monkeypatch, lambda: OracleGraph(vecs, codes).graph_of(np.arange(300), (0, 299)))
    assert beams == 0 and hits(OracleGraph(vecs, codes), vecs, codes) > 0.95
    assert held.links[0][1] and all(r != i for i, to in enumerate(held.links[0]) for r in to)


def test_rows_that_have_not_arrived_or_are_deleted_are_no_candidates():
    vecs, codes = data(40)
    held = Stack(vecs, codes, Settings(layers=1, o=1 << 40, scan=True))
    for row in (30, 2, 17):
        held.insert(row)
    held.deleted[2] = True
    assert set(held.nearest(stack.far(vecs, slice(0, 31), vecs[5]), (0, 39), 64).rows) == {30, 17}


def test_graphs_of_blocks_are_built_without_searches(monkeypatch):
    vecs, codes = data()
    held, beams = searched(monkeypatch, lambda: BlockSuperset(vecs, codes))
    assert beams == 0 and hits(held, vecs, codes) > 0.95
