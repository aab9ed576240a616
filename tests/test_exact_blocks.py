"""Exact search for many narrow ranges, block by block of values: no table of pairs, copies folded, ties by id."""

from pyspark.sql import functions as F

from hybridrange import exact, workloads
from hybridrange.methods import asked


def test_blocks_answer_as_brute_force(spark):
    # 40 copies of a vector at one value, more than k; ids fall while values rise; one row without a vector, one without a value
    data = spark.createDataFrame([(900 - i, [float(i % 3), float(i % 2)], i // 40) for i in range(600)] + [(1000, None, 4), (1001, [0.0, 0.0], None)], "id long, vec array<double>, attr long")
    q = spark.createDataFrame([(1, [0.0, 0.4], 0, 3), (2, [1.0, 1.0], 4, 4), (3, [2.0, 0.0], 9, 5), (4, [0.5, 0.5], 3, 14), (1, [2.0, 2.0], 14, 14), (5, [0.0, 0.0], 40, 50)], "qid long, qvec array<double>, lo long, hi long")
    want = {}
    for x in q.collect():
        far = lambda r, x=x: None if r.vec is None else sum((a - b) ** 2 for a, b in zip(r.vec, x.qvec, strict=True)) ** 0.5
        want.setdefault(x.qid, []).extend((far(r) is None, far(r) or 0.0, r.id) for r in data.collect() if r.attr is not None and x.lo <= r.attr <= x.hi)
    found = exact._finished(exact.nearest_in_blocks(data, q, 25, lambda c: F.floor(F.col(c) / 4)), 25)
    got = {(r.qid, r.pos): r.id for r in found.collect()}
    assert got == {(i, n + 1): t[2] for i, pool in want.items() for n, t in enumerate(sorted(pool)[:25])}


def test_exact_line_makes_no_pairs(spark, sf_dir):
    data, q = asked(spark, sf_dir, "line", fixed=8)
    plan = workloads.exact_line(spark, sf_dir)._jdf.queryExecution().toString()
    assert data.count() and q.count() and "FlatMapCoGroupsInArrow" in plan and "Join" not in plan
