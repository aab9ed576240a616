"""Streams over the events: windows, deduplication, joins, state, and insertion into an index.

Each query runs its stream to the end of the input (``availableNow``) and
returns the sink's table, so that a batch twin can be its oracle.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hybridrange import index, measures
from hybridrange.exact import exact_range_knn, top_k
from hybridrange.hybrid import hybrid, make_ranges, ranges_sql
from hybridrange.plans.tables import cut, fresh_path, table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def op(name: str, oracle: str | None):
    def put(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


def stream(spark: SparkSession, sf_dir: str, name: str = "events", files: int = 4) -> DataFrame:
    """A table as a stream of ``files`` files in order of their rows, one a trigger."""
    rows, path = table(spark, sf_dir, name), fresh_path(spark, f"{name}-files")
    rows.repartitionByRange(files, rows.columns[0]).write.parquet(path)
    found = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return found.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in found.columns else found


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """The rows that a stream writes until its input ends."""
    spark = df.sparkSession
    path, place = fresh_path(spark, "sink"), fresh_path(spark, "state")
    if mode == "append":
        run = df.writeStream.format("parquet").option("path", path).option("checkpointLocation", place).trigger(availableNow=True).start()
    else:  # the last version of every group: each batch replaces the table

        def replace(rows: DataFrame, batch: int) -> None:
            rows.write.mode("overwrite").parquet(path)

        run = df.writeStream.outputMode("complete").foreachBatch(replace).option("checkpointLocation", place).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def ntz(name: str):
    return F.col(name).cast("timestamp_ntz")


@op("source_stream_files", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(spark, sf_dir):
    return drained(stream(spark, sf_dir).select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@op("sink_foreach_batch", "SELECT event_id, value FROM events WHERE value > 50")
def _(spark, sf_dir):
    path = fresh_path(spark, "batches")

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch}")  # a batch that is tried again replaces itself

    kept = stream(spark, sf_dir).where("value > 50").select("event_id", "value")
    kept.writeStream.foreachBatch(put).option("checkpointLocation", fresh_path(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(path).select("event_id", "value")


@op("st_tumbling", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    w = stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("n"))
    return drained(w, "complete").select(ntz("window.start").alias("start"), "event_type", "n")


@op("st_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 3 HOUR]) AS s FROM events) GROUP BY s")
def _(spark, sf_dir):
    w = stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "6 hours", "3 hours")).agg(F.count("*").alias("n"))
    return drained(w, "complete").select(ntz("window.start").alias("start"), "n")


@op("st_session", "WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def _(spark, sf_dir):
    w = stream(spark, sf_dir).withWatermark("ts", "365 days").groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count("*").alias("n"))
    return drained(w, "complete").select("user_id", ntz("session_window.start").alias("start"), "n")


@op("st_dedup", "SELECT count(*) AS n FROM events")
def _(spark, sf_dir):
    """Every event is sent twice; the second within the watermark is dropped."""
    once = stream(spark, sf_dir)
    twice = once.union(stream(spark, sf_dir)).withWatermark("ts", "365 days").dropDuplicatesWithinWatermark(["event_id"])
    return drained(twice.select("event_id")).agg(F.count("*").alias("n"))


@op("st_late_rows", "SELECT date_trunc('hour', ts) AS start, count(*) AS n, true AS no_more FROM events GROUP BY 1 HAVING date_trunc('hour', ts) + INTERVAL 61 MINUTE <= (SELECT max(ts) FROM events)")
def _(spark, sf_dir):
    """Windows that the watermark closes when all rows come at once, and that none of them gains rows when later files bring some behind the watermark."""
    counts = lambda files: drained(stream(spark, sf_dir, files=files).withWatermark("ts", "1 minute").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))).select(ntz("window.start").alias("start"), "n")
    late = counts(4).withColumnRenamed("n", "m")
    return counts(1).join(late, "start", "left").select("start", "n", (F.coalesce("m", F.lit(0)) <= F.col("n")).alias("no_more"))


@op("st_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def _(spark, sf_dir):
    return drained(stream(spark, sf_dir).join(table(spark, sf_dir, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@op("st_stream_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, sf_dir):
    """Pairs of a user's events within an hour, of two streams with watermarks."""
    a = stream(spark, sf_dir).withWatermark("ts", "365 days").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"))
    b = stream(spark, sf_dir).withWatermark("ts", "365 days").select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb"))
    return drained(a.join(b, F.expr("u = v and tb > ta and tb <= ta + interval 1 hour")).select("a", "b"))


@op("st_stateful_counts", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def _(spark, sf_dir):
    """Running counts of each user in keyed state; the last one stands."""

    def count(key, frames, state):
        n = state.get[0] if state.exists else 0
        n += sum(len(x) for x in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    kept = stream(spark, sf_dir).groupBy("user_id").applyInPandasWithState(count, "user_id long, n long", "n long", "update", "NoTimeout")
    path = fresh_path(spark, "state-counts")

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    kept.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", fresh_path(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(path).groupBy("user_id").agg(F.max("n").alias("n"))


@op("st_insert_index", f"WITH {ranges_sql('time')} SELECT qid, least(10, count(attr)) AS n_found, true AS recall_ok FROM q LEFT JOIN h ON attr >= lo AND attr <= hi GROUP BY qid")
def _(spark, sf_dir):
    """Arrivals go into the index batch by batch: each batch makes segments of its own by time, and queries merge all."""
    data, root = hybrid(spark, sf_dir, "time"), fresh_path(spark, "segments")
    files = fresh_path(spark, "arrivals")
    data.repartitionByRange(3, "attr").write.parquet(files)

    def insert(rows: DataFrame, batch: int) -> None:
        index.build_index(rows, order="sorted").withColumn("seg", F.lit(batch << 32).cast("long") + F.col("seg")).write.mode("overwrite").parquet(f"{root}/batch={batch}")

    arrivals = spark.readStream.schema(data.schema).option("maxFilesPerTrigger", 1).parquet(files)
    arrivals.writeStream.foreachBatch(insert).option("checkpointLocation", fresh_path(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    q = cut(make_ranges(data), "asked")
    held = spark.read.parquet(root).drop("batch")
    # ranks are local to a batch, so values are compared as times and codes stay within their segment
    found = top_k(index.search(held, q, 10).where("id is not null").select("qid", "id", "dist"), 10)
    ok = measures.recall(found, exact_range_knn(data, q, 10), 10).agg((F.avg("recall") >= 0.95).alias("recall_ok"))
    return q.select("qid").join(found.groupBy("qid").agg(F.count("*").alias("n_found")), "qid", "left").select("qid", F.coalesce("n_found", F.lit(0)).alias("n_found")).crossJoin(F.broadcast(ok))  # one row


@op("stream_batch_twin", "SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nth FROM events")
def _(spark, sf_dir):
    """Rows written by a stream, numbered in a batch."""
    rows = drained(stream(spark, sf_dir).select("user_id", "event_id", "ts"))
    return rows.select("user_id", "event_id", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long").alias("nth"))


