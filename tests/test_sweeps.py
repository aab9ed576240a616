"""An index is built once for all that is asked of it, and sized without being searched."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrange import exact, workloads
from hybridrange.baselines import run


@pytest.fixture(scope="module")
def asked(spark):
    rng = np.random.default_rng(2)
    data = spark.createDataFrame([(i, [float(x) for x in rng.normal(size=4)], i) for i in range(240)], "id long, vec array<float>, attr long")
    q = data.where("id % 20 = 0").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    return data, [q.select("qid", "qvec", F.lit(a).cast("long").alias("lo"), F.lit(b).cast("long").alias("hi")) for a, b in ((0, 200), (30, 90))]


def rows(df, *names):
    return sorted(tuple(r[c] for c in names) for r in df.collect())


def test_one_build_answers_as_one_for_each_way_and_set(asked):
    data, sets = asked
    hows = ({"landing": "auto"}, {"landing": "top"})
    names = ("qid", "omega", "id", "dist", "dc", "fc")
    every = run.run_kind("window_stack", data, sets[0].withColumn("set", F.lit(0)).union(sets[1].withColumn("set", F.lit(1))), 5, (8, 16), cap=100, hows=hows)
    apart = {(w, s): run.run_kind("window_stack", data, sets[s], 5, (8, 16), cap=100, how=hows[w]) for w in (0, 1) for s in (0, 1)}
    truth = [exact.exact_range_knn(data, x, 5) for x in sets]
    both = workloads.points(every, truth[0].withColumn("set", F.lit(0)).union(truth[1].withColumn("set", F.lit(1))), 5, ("way", "set"))
    for (w, s), one in apart.items():
        here = lambda x, w=w, s=s: x.where((F.col("way") == w) & (F.col("set") == s))
        key = lambda r: tuple((v is None, v) for v in r)
        got, want = ([tuple(r[c] for c in names) for r in x.collect()] for x in (here(every), one))
        assert sorted(got, key=key) == sorted(want, key=key)
        assert rows(here(both), "omega", "recall", "dc", "fc") == rows(workloads.points(one, truth[s], 5), "omega", "recall", "dc", "fc")


def test_sizes_cover_segments_that_no_range_meets(asked):
    data, _ = asked
    held = run.sizes("flat_graph", data, cap=100)
    assert held.count() == 3 and held.agg(F.sum("bytes")).first()[0] == 240 * 16 * 4 and held.where("build_s > 0").count() == 3


def test_index_cost_searches_nothing(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(run, "run_kind", lambda *a, **b: pytest.fail("an index was searched"))
    assert workloads.index_cost(spark, sf_dir).columns == ["index", "dataset", "bytes", "build_s"]


def test_index_cost_covers_every_index_on_every_set(spark, sf_dir, monkeypatch):
    every = workloads.hybrid
    monkeypatch.setattr(workloads, "hybrid", lambda *a: every(*a).where("id < 60"))
    got = workloads.index_cost(spark, sf_dir).collect()
    kinds, sets = set(workloads.FLOORS), ("rand", "time", "title", "id")
    assert sorted((r["index"], r["dataset"]) for r in got) == sorted((k, d) for k in kinds for d in sets)
    for name in sets:
        data = workloads.hybrid(spark, sf_dir, name)
        for kind in ("prefilter", "flat_graph", "ivf"):
            want = run.sizes(kind, data).agg(F.sum("bytes")).first()[0]
            assert [r["bytes"] for r in got if (r["index"], r["dataset"]) == (kind, name)] == [want]
        assert all(r["build_s"] > 0 for r in got if r["index"] == "flat_graph")


def test_segments_of_a_half_leave_room_for_the_other(spark, sf_dir, monkeypatch):
    caps, build = [], workloads.index.build_index
    monkeypatch.setattr(workloads.index, "build_index", lambda data, *a, cap=workloads.index.CAP, **b: caps.append(cap) or build(data, *a, cap=cap, **b))
    monkeypatch.setattr(workloads, "held", lambda spark, key, make: make())
    workloads.halves(spark, sf_dir, "window_stack", False)
    assert caps == [workloads.index.CAP // 2]
