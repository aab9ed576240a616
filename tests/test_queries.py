"""Queries against their oracles on the smallest tables, and the edge cases of the DataFrame side."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

from hybridrange import exact, index, measures, ranks, registry
from hybridrange.layers import landing_layer, landing_layer_col, top_layer, top_layer_col

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAMPLE = ["exact_range_knn", "exact_range_knn_title", "dense_ranks_label", "range_counts_dup50", "median_row", "window_bounds_1", "landing_layer", "window_knn_graph_1", "diverse_graph_1", "postfilter_exact", "in_range_fraction", "lid", "recall", "range_knn_price", "join_bucketed_range", "join_skew_salted", "agg_rollup", "win_two_phase_rank", "st_tumbling", "exact_lex", "range_knn_lex", "range_knn_infilter", "range_knn_merge", "udtf_range_knn", "sql_landing", "range_knn_updated", "sample_stratified"]


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 9) + 0.0)
    if isinstance(v, list | tuple):
        return str([plain(x) for x in v])
    return str(v)


@pytest.fixture(scope="module")
def db(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", SAMPLE)
def test_oracle(spark, sf_dir, db, name):
    df = registry.queries()[name](spark, sf_dir)
    other = db.sql(registry.oracles()[name])
    names = sorted(df.columns)
    assert names == sorted(other.columns)
    got = sorted(tuple(plain(r[c]) for c in names) for r in df.collect())
    at = [other.columns.index(c) for c in names]
    assert got == sorted(tuple(plain(r[i]) for i in at) for r in other.fetchall())


def test_every_oracle_has_a_query():
    assert set(registry.oracles()) <= set(registry.queries()) and len(registry.queries()) > 200


def test_layer_columns_equal_the_integers(spark):
    rows = spark.range(1, 400).select("id", *[top_layer_col(F.col("id"), o).alias(f"t{o}") for o in (2, 3, 4, 10)], *[landing_layer_col(F.col("id"), o, F.lit(3)).alias(f"l{o}") for o in (2, 3, 4, 10)]).collect()
    for r in rows:
        for o in (2, 3, 4, 10):
            assert r[f"t{o}"] == top_layer(r["id"], o) and r[f"l{o}"] == landing_layer(r["id"], o, 3)


def rows(spark, values):
    return spark.createDataFrame([(i, [float(i), float(i % 3)], v) for i, v in enumerate(values)], "id long, vec array<float>, attr long")


def test_null_attributes_are_never_in_range(spark):
    data = rows(spark, [5, None, 7, None, 5])
    q = spark.createDataFrame([(1, [0.0, 0.0], None, None), (2, [0.0, 0.0], 9, 3), (3, [0.0, 0.0], 5, 5)], "qid long, qvec array<float>, lo long, hi long")
    got = {(r.qid, r.id) for r in exact.exact_range_knn(data, q, 10).collect()}
    assert got == {(1, 0), (1, 2), (1, 4), (3, 0), (3, 4)}
    assert {(r.attr, r.mult, r.rank_u, r.before) for r in ranks.order_stats(data).collect()} == {(5, 2, 0, 0), (7, 1, 1, 2)}


def test_empty_tables(spark):
    data = rows(spark, [])
    q = spark.createDataFrame([(1, [0.0, 0.0], 1, 2)], "qid long, qvec array<float>, lo long, hi long")
    assert exact.exact_range_knn(data, q, 10).count() == 0 and ranks.order_stats(data).count() == 0
    assert ranks.range_counts(ranks.order_stats(data), q).collect()[0].n_rows == 0


def test_hot_value_is_dealt_to_sub_segments(spark):
    data = rows(spark, [3] * 120 + list(range(10, 40)))
    held = index.build_index(data, cap=50)
    assert held.where("attr = 3").select("sub").distinct().count() == 3
    q = spark.createDataFrame([(1, [0.0, 0.0], 3, 12)], "qid long, qvec array<float>, lo long, hi long")
    truth = exact.exact_range_knn(data, q, 10)
    found = index.range_knn(held, q, 10)
    assert measures.recall(found, truth, 10).first().recall == 1.0


def test_a_search_moves_queries_and_results_only(spark, tmp_path):
    data = rows(spark, list(range(300)))
    index.packed(index.build_index(data, cap=100)).write.parquet(f"{tmp_path}/parts")
    held = spark.read.parquet(f"{tmp_path}/parts")
    q = spark.createDataFrame([(1, [0.0, 0.0], 3, 12), (2, [0.0, 0.0], 40, 30)], "qid long, qvec array<float>, lo long, hi long")
    found = index.search(held, q, 10)
    plan = found._jdf.queryExecution().executedPlan().toString()
    scan = plan.index("payload")
    above = plan[:scan].splitlines()
    assert held.count() == 3 and not any("Exchange hashpartitioning" in x or "SortMergeJoin" in x for x in above) and "PushedFilters: [IsNotNull(attr_hi)" in plan + found._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert {(r.qid, r.id) for r in found.collect()} == {(1, i) for i in range(3, 13)}


def test_insertion_routes_each_row_to_one_segment(spark):
    data = rows(spark, [3] * 120 + list(range(10, 200)))
    held = index.build_index(data, cap=50)
    new = rows(spark, [None, 3, 3, 3, 5, 1, 500]).withColumn("id", F.col("id") + 1000)
    grown = index.insert(held, new)
    assert grown.count() == 316 and grown.where("id >= 1000").select("id").distinct().count() == 6
    again = index.update(grown, new.where("id = 1006").withColumn("attr", F.lit(4).cast("long")))
    q = spark.createDataFrame([(1, [0.0, 0.0], 4, 5), (2, [0.0, 0.0], 400, 600)], "qid long, qvec array<float>, lo long, hi long")
    assert {(r.qid, r.id) for r in index.range_knn(again, q, 10).collect()} == {(1, 1004), (1, 1006)}


def test_printed_example_of_the_share_in_range(spark):
    from hybridrange import theory

    r = theory.fraction_table(spark, [2048], [2]).first()
    assert r.case == "c" and round(r.low, 4) == 0.7498 and round(r.high, 3) == 0.823


def test_lid_of_three_distances(spark):
    t = spark.createDataFrame([(1, i, d) for i, d in enumerate((1.0, 2.0, 4.0))], "qid long, id long, dist double")
    assert measures.lid(t).first().lid == 1.4427


def test_recall_with_few_rows(spark):
    t = spark.createDataFrame([(1, i) for i in range(4)], "qid long, id long")
    assert measures.recall(t.where("id < 3"), t, 10).first().recall == 0.75


def test_names_are_known_without_a_session():
    import subprocess
    import sys

    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; assert len(e.queries()) > 200 and e.oracle_sql()"], capture_output=True, text=True, timeout=120)
    assert said.returncode == 0, said.stderr[-500:]


def test_counts_by_end_points_against_a_plain_count(spark):
    values = [3] * 4 + [5, 5, 8, 13, 13, 21, 34] * 9
    asked = [(1, 3, 3), (2, 4, 4), (3, 5, 13), (4, -9, 99), (5, 13, 5), (6, 35, 40), (7, -5, 2), (8, 22, 34), (9, None, 8), (10, 0, 21)]
    stats = ranks.order_stats(rows(spark, values))
    q = spark.createDataFrame(asked, "qid long, lo long, hi long")
    inside = {i: sorted(v for v in values if lo is not None and lo <= v <= hi) for i, lo, hi in asked}
    counts = ranks.range_counts(stats, q)
    assert {(r.qid, r.n_rows, r.n_uniques) for r in counts.collect()} == {(i, len(x), len(set(x))) for i, x in inside.items()}
    assert {(r.qid, r.median_attr) for r in ranks.median_rows(stats, q).collect()} == {(i, x[(len(x) - 1) // 2]) for i, x in inside.items() if x}
