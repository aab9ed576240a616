"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from hybridrange import methods, registry

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
HEADLINE = ["exact_range_knn", "exact_line", "prefilter_knn", "postfilter_exact", "dense_ranks_line", "range_counts", "window_knn_graph_2", "diverse_graph_2", "range_knn_segments", "baseline_multiway_tree", "join_bucketed_range", "win_two_phase_rank"]


def stages(spark: SparkSession) -> dict[str, float]:
    """The stack's build and its answers to the stated queries, apart; the queries themselves are written before either."""
    from hybridrange import index, methods

    took, clock = {}, time.perf_counter
    _, asked = methods.asked(spark, SF_DIR)
    asked.count()
    began = clock()
    parts = methods.packed(spark, SF_DIR)
    took["range_knn_build"] = round(clock() - began, 3)
    for name, how in (("range_knn", {}), ("range_knn_no_early_stop", {"early_stop": False}), ("range_knn_forced_top", {"landing": "top"})):
        began = clock()
        index.range_knn(parts, asked, complete=False, **how).write.format("noop").mode("overwrite").save()
        took[name] = round(clock() - began, 3)
    return took


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    queries, took = registry.queries(), {}
    spark.range(1000).selectExpr("sum(id)").collect()
    for name in HEADLINE:
        methods._HELD.clear()  # each query pays for what it needs
        began = time.perf_counter()
        queries[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
    methods._HELD.clear()
    took |= stages(spark)
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": float(SF_DIR.rstrip("/").rsplit("sf", 1)[-1] or 0)}))
    spark.stop()


if __name__ == "__main__":
    main()
