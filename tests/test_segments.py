"""Segments stay small, and what is summed or kept for each of them; strict windows make one graph."""

import numpy as np
from pyspark.sql import functions as F

from hybridrange import index, workloads
from hybridrange.baselines.kernels import OracleGraph
from hybridrange.kernel.stack import Settings, Stack


def test_strict_windows_make_one_graph():
    for seed in range(6):
        vecs = np.random.default_rng(seed).normal(size=(300, 16))
        stack = Stack(vecs, np.random.default_rng(seed + 50).permutation(300), Settings(strict=True)).build()
        near = [set() for _ in vecs]
        for layer in stack.links:
            for a, to in enumerate(layer):
                for b in to:
                    near[a].add(b)
                    near[b].add(a)
        seen, todo = {0}, [0]
        while todo:
            new = near[todo.pop()] - seen
            seen |= new
            todo += new
        assert len(seen) == 300


def test_an_index_grows_by_segments(spark):
    rng = np.random.default_rng(3)
    data = spark.createDataFrame([(i, [float(x) for x in rng.normal(size=4)], i) for i in range(1300)], "id long, vec array<float>, attr long")
    sizes = [r.n for r in index.segmented(data).groupBy("seg", "sub").agg(F.count("*").alias("n")).collect()]
    assert len(sizes) > 1 and sum(sizes) == 1300
    held = index.build_index(data.where("id < 60"), cap=20)
    assert {r.n for r in held.select(F.size("links").alias("n")).collect()} == {4}  # 2 * 4**2 < 60 <= 2 * 4**3
    parts = spark.createDataFrame([(s, 0, q, 100 * (s + 1), 0.5) for s in range(3) for q in range(2)], "seg long, sub int, qid long, bytes long, build_s double")
    assert tuple(workloads.built_size(parts).first()) == (600, 1.5)


def test_a_kept_graph_answers_as_a_new_one():
    rng = np.random.default_rng(5)
    vecs, codes = rng.normal(size=(80, 8)), rng.permutation(80)
    asked = [((0, 79), 1), ((10, 60), 2), ((10, 60), 3), ((0, 79), 4), ((20, 30), 5)]
    kept = OracleGraph(vecs, codes)
    for bounds, row in asked:
        a, b = kept.query(vecs[row], bounds, 5, 16), OracleGraph(vecs, codes).query(vecs[row], bounds, 5, 16)
        assert (a.rows, a.dist, a.dc) == (b.rows, b.dist, b.dc) and len(kept.kept_graphs) <= 2
