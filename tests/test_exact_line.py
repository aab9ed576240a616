"""Exact search over the line items against brute force."""

import numpy as np

from hybridrange import workloads
from hybridrange.methods import K, asked


def test_exact_line_asks_every_twentieth_row(spark, sf_dir):
    data, q = asked(spark, sf_dir, "line", fixed=8)
    rows, queries = data.collect(), q.collect()
    assert queries and {x.qid for x in queries} == {x.id for x in rows if x.id % 20 == 0}
    attrs = np.array([x.attr for x in rows], "datetime64[us]")
    vecs = np.array([x.vec for x in rows], np.float64)
    got = {}
    for x in workloads.exact_line(spark, sf_dir).collect():
        got.setdefault(x.qid, []).append((x.pos, x.id, x.dist))
    assert set(got) == {x.qid for x in queries}
    want = {}
    for x in queries:  # line items may repeat an id, and with it a query's name
        inside = np.flatnonzero((attrs >= np.datetime64(x.lo, "us")) & (attrs <= np.datetime64(x.hi, "us")))
        dist = np.sqrt(((vecs[inside] - np.array(x.qvec, np.float64)) ** 2).sum(1))
        want.setdefault(x.qid, []).extend(dist.tolist())
    for qid, dist in want.items():
        assert np.allclose([d for *_, d in sorted(got[qid])], sorted(dist)[:K], atol=2e-6)
