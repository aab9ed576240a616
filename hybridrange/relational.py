"""The relational operators around range-filtered search: what a user needs before, during and after it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window, WindowSpec
from pyspark.sql import functions as F

from hybridrange.functions import vectors as V
from hybridrange.hybrid import SCALE, hybrid, hybrid_sql, l2sq_sql
from hybridrange.plans.tables import fresh_path, table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


class Tables:
    """``t.events`` reads a table."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return table(self.spark, self.sf_dir, name)

    def h(self, name: str = "rand") -> DataFrame:
        return hybrid(self.spark, self.sf_dir, name)


def op(name: str, oracle: str | None, f: Callable[[Tables], DataFrame]) -> None:
    QUERIES[name] = lambda spark, sf_dir: f(Tables(spark, sf_dir))
    if oracle is not None:
        ORACLES[name] = oracle


c = F.col
H, D50 = hybrid_sql("rand"), hybrid_sql("dup50")

# Scans, sources and sinks ---------------------------------------------------

op("scan_pruned", "SELECT p_partkey, p_retailprice FROM part WHERE p_retailprice BETWEEN 950 AND 1100", lambda t: t.part.where("p_retailprice between 950 and 1100").select("p_partkey", "p_retailprice"))
op("scan_schema_checked", "SELECT count(*) AS n, count(*) FILTER (WHERE len(embedding) <> 64) AS bad FROM embeddings", lambda t: t.spark.read.schema("vec_id long, embedding array<float>, label int").parquet(f"{t.sf_dir}/embeddings.parquet").agg(F.count("*").alias("n"), F.count_if(F.size("embedding") != 64).alias("bad")))


def round_trip(t: Tables, form: str) -> DataFrame:
    """Prices written and read again in one format; vectors as JSON text where the format has no arrays."""
    rows, path = t.h("price").select("id", "attr", F.to_json("vec").alias("vec")), fresh_path(t.spark, form)
    rows.write.format(form).save(path)
    back = t.spark.read.format(form).schema("id long, attr double, vec string").load(path)
    return back.select("id", "attr", F.size(F.from_json("vec", "array<float>")).alias("d"))


for _form in ("csv", "json", "orc"):
    op(f"scan_{_form}", f"SELECT id, attr, 64 AS d FROM ({hybrid_sql('price')})", lambda t, form=_form: round_trip(t, form))


def partitioned(t: Tables) -> DataFrame:
    path = fresh_path(t.spark, "by-label")
    t.embeddings.write.partitionBy("label").parquet(path)
    return t.spark.read.parquet(path).where("label = 3").select("vec_id", c("label").cast("int").alias("label"))


op("scan_partitioned", "SELECT vec_id, label FROM embeddings WHERE label = 3", partitioned)


def overwritten(t: Tables) -> DataFrame:
    """Replaces only the partitions that the new rows touch."""
    path = fresh_path(t.spark, "dynamic")
    t.part.select("p_partkey", "p_size").write.partitionBy("p_size").parquet(path)
    t.part.where("p_size = 7").select((c("p_partkey") + 1_000_000).alias("p_partkey"), "p_size").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("p_size").parquet(path)
    return t.spark.read.parquet(path).select("p_partkey", c("p_size").cast("int").alias("p_size"))


op("sink_overwrite_dynamic", "SELECT CASE WHEN p_size = 7 THEN p_partkey + 1000000 ELSE p_partkey END AS p_partkey, p_size FROM part", overwritten)


def manifested(t: Tables) -> DataFrame:
    """Data first and the manifest row last: a version without a manifest row is never read."""
    root = fresh_path(t.spark, "versions")
    for version, rows in enumerate((t.h().where("attr < 500000"), t.h())):
        rows.select("id", "attr").write.parquet(f"{root}/data/{version}")
        t.spark.createDataFrame([(version, f"{root}/data/{version}")], "version int, path string").coalesce(1).write.mode("append").parquet(f"{root}/manifest")
    t.h().limit(1).select("id", "attr").write.parquet(f"{root}/data/2")  # not committed
    last = t.spark.read.parquet(f"{root}/manifest").agg(F.max_by("path", "version")).first()[0]
    return t.spark.read.parquet(last)


op("sink_manifest", f"SELECT id, attr FROM ({H})", manifested)

# Vectors --------------------------------------------------------------------

op("vec_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x))), 6) AS n FROM embeddings", lambda t: t.embeddings.select("vec_id", F.round(V.norm("embedding"), 6).alias("n")))
op("vec_normalize", "SELECT vec_id, round((embedding[1]::DOUBLE) / sqrt(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x))), 6) AS first FROM embeddings", lambda t: t.embeddings.select("vec_id", F.round(F.get(V.normalize("embedding"), F.lit(0)), 6).alias("first")))
_PAIR = "FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


def neighbours(t: Tables) -> DataFrame:
    a, b = t.embeddings.select("vec_id", c("embedding").alias("a")), t.embeddings.select((c("vec_id") - 1).alias("vec_id"), c("embedding").alias("b"))
    return a.join(b, "vec_id")


op("vec_l2sq", f"SELECT a.vec_id, round({l2sq_sql('a.embedding', 'b.embedding')}, 6) AS d {_PAIR}", lambda t: neighbours(t).select("vec_id", F.round(V.l2sq("a", "b"), 6).alias("d")))
op("vec_dot", f"SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), lambda t: t[1] * t[2])), 6) AS d {_PAIR}", lambda t: neighbours(t).select("vec_id", F.round(V.dot("a", "b"), 6).alias("d")))
op("vec_cosine", f"SELECT a.vec_id, round({__import__('hybridrange.hybrid', fromlist=['x']).cosine_sql('a.embedding', 'b.embedding')}, 6) AS d {_PAIR}", lambda t: neighbours(t).select("vec_id", F.round(V.cosine("a", "b"), 6).alias("d")))
op("vec_add_scale", f"SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), lambda t: t[1] + 0.5 * t[2])), 6) AS s {_PAIR}", lambda t: neighbours(t).select("vec_id", F.round(V.total(V.add_scaled("a", "b", 0.5)), 6).alias("s")))
op("vec_slice_dims", "SELECT vec_id, round(list_sum(embedding[1:8]::DOUBLE[]), 6) AS s, embedding[64]::DOUBLE AS final FROM embeddings", lambda t: t.embeddings.select("vec_id", F.round(V.total(F.transform(F.slice("embedding", 1, 8), lambda x: x.cast("double"))), 6).alias("s"), F.element_at("embedding", -1).cast("double").alias("final")))

# Filters --------------------------------------------------------------------

op("filter_closed_range", f"SELECT id FROM ({H}) WHERE attr BETWEEN 200000 AND 400000", lambda t: t.h().where(c("attr").between(200000, 400000)).select("id"))
op("filter_half_open", f"SELECT id FROM ({H}) WHERE attr >= 200000 AND attr < 400000", lambda t: t.h().where("attr >= 200000 and attr < 400000").select("id"))
op("filter_one_sided", f"SELECT id FROM ({H}) WHERE attr >= 700000", lambda t: t.h().where(F.coalesce(c("attr") >= F.lit(700000), F.lit(True)) & F.coalesce(c("attr") <= F.lit(None).cast("long"), F.lit(True))).select("id"))
op("filter_string_range", "SELECT page_id FROM pages WHERE url BETWEEN 'http' AND 'https://m'", lambda t: t.pages.where(c("url").between("http", "https://m")).select("page_id"))
op("filter_time_range", "SELECT event_id FROM events WHERE ts >= (SELECT min(ts) FROM events) + INTERVAL 1 DAY AND ts <= (SELECT min(ts) FROM events) + INTERVAL 3 DAY", lambda t: t.events.crossJoin(F.broadcast(t.events.agg(F.min("ts").alias("t0")))).where("ts >= t0 + interval 1 day and ts <= t0 + interval 3 day").select("event_id"))
op("filter_in_list", "SELECT p_partkey FROM part WHERE p_size IN (1, 5, 9)", lambda t: t.part.where(c("p_size").isin(1, 5, 9)).select("p_partkey"))
op("filter_like", "SELECT p_partkey FROM part WHERE p_type LIKE '%A%'", lambda t: t.part.where(c("p_type").like("%A%")).select("p_partkey"))
op("filter_regex", "SELECT page_id FROM pages WHERE regexp_matches(url, '[0-9]{2}')", lambda t: t.pages.where(c("url").rlike("[0-9]{2}")).select("page_id"))
op("filter_null_attr", "SELECT vec_id FROM embeddings WHERE nullif(label, 3) IS NULL", lambda t: t.embeddings.where(F.nullif("label", F.lit(3)).isNull()).select("vec_id"))
op("filter_empty_range", f"SELECT id FROM ({H}) WHERE attr BETWEEN 400000 AND 200000", lambda t: t.h().where(c("attr").between(400000, 200000)).select("id"))
op("filter_disjunction", f"SELECT id FROM ({H}) WHERE attr BETWEEN 100000 AND 300000 OR attr BETWEEN 250000 AND 500000", lambda t: t.h().where(c("attr").between(100000, 300000) | c("attr").between(250000, 500000)).select("id"))

# Joins ----------------------------------------------------------------------

_OC = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"
for _key, _hint in (("join_broadcast_hash", "broadcast"), ("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    op(_key, _OC, lambda t, hint=_hint: t.orders.join(t.customer.hint(hint), c("o_custkey") == c("c_custkey")).select("o_orderkey", "c_mktsegment"))


def spans(t: Tables) -> DataFrame:
    """A stated query set of ranges, one per label."""
    return t.embeddings.select(c("label").alias("qid")).distinct().select("qid", (c("qid") * 90000).cast("long").alias("lo"), (c("qid") * 90000 + 120000).cast("long").alias("hi"))


_SPANS = "(SELECT DISTINCT label AS qid, label * 90000 AS lo, label * 90000 + 120000 AS hi FROM embeddings)"
_RANGE_JOIN = f"SELECT qid, id FROM ({H}) JOIN {_SPANS} ON attr BETWEEN lo AND hi"
op("join_nested_loop_range", _RANGE_JOIN, lambda t: t.h().join(F.broadcast(spans(t)), c("attr").between(c("lo"), c("hi"))).select("qid", "id"))


def bucketed_range(t: Tables) -> DataFrame:
    """Ranges are dealt to the buckets that they cover, rows to their own: an equality join with the range as residue."""
    size = 50_000
    q = spans(t).withColumn("b", F.explode(F.sequence(F.floor(c("lo") / size), F.floor(c("hi") / size))))
    return t.h().withColumn("b", F.floor(c("attr") / size)).join(q, "b").where("attr between lo and hi").select("qid", "id")


op("join_bucketed_range", _RANGE_JOIN, bucketed_range)


def band(t: Tables) -> DataFrame:
    from hybridrange import graphs, ranks

    return graphs.window_pairs(ranks.with_ranks(t.h()), 4, 1).select("src", "dst")


op("join_band", f"WITH h AS (SELECT id, dense_rank() OVER (ORDER BY attr) AS r FROM ({H})) SELECT a.id AS src, b.id AS dst FROM h a JOIN h b ON a.id <> b.id AND abs(a.r - b.r) <= 4", band)


def near_events(t: Tables) -> DataFrame:
    """Events of different users within ten minutes, by time buckets of that width."""
    e = t.events.select("event_id", "user_id", F.unix_micros(c("ts").cast("timestamp")).alias("us"))
    width = 600_000_000
    a = e.withColumn("b", F.floor(c("us") / width))
    b = e.select(c("event_id").alias("other"), c("user_id").alias("u2"), c("us").alias("us2"), F.explode(F.array(*[F.floor(c("us") / width) + i for i in (-1, 0, 1)])).alias("b"))
    return a.join(b, "b").where((c("event_id") < c("other")) & (c("user_id") != c("u2")) & (F.abs(c("us") - c("us2")) <= width)).select("event_id", "other")


op("join_interval_events", "SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.event_id < b.event_id AND a.user_id <> b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000", near_events)


def as_of(t: Tables) -> DataFrame:
    """Each event with the value of the user's last purchase-like event at or before it: a union sorted by time, filled forward."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return t.events.select("event_id", F.last("value", ignorenulls=True).over(w).alias("before"))


op("join_asof", "SELECT a.event_id, (SELECT b.value FROM events b WHERE b.user_id = a.user_id AND (b.ts < a.ts OR b.ts = a.ts AND b.event_id < a.event_id) ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) AS before FROM events a", as_of)
op("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", lambda t: t.customer.join(t.orders, c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"))
op("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", lambda t: t.customer.join(t.orders, c("c_custkey") == c("o_custkey"), "left_anti").select("c_custkey"))
op("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey", lambda t: t.customer.join(t.orders, c("c_custkey") == c("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
op("join_outer_full", "SELECT vec_id, page_id FROM embeddings FULL JOIN pages ON vec_id = page_id", lambda t: t.embeddings.join(t.pages, c("vec_id") == c("page_id"), "full").select("vec_id", "page_id"))
op("join_cross", "SELECT n_nationkey, r_regionkey FROM nation, region", lambda t: t.nation.crossJoin(F.broadcast(t.region)).select("n_nationkey", "r_regionkey"))
op("join_self", "SELECT a.p_partkey AS p, b.p_partkey AS q FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey", lambda t: t.part.select(c("p_partkey").alias("p"), "p_brand", "p_size").join(t.part.select(c("p_partkey").alias("q"), "p_brand", "p_size"), ["p_brand", "p_size"]).where("p < q").select("p", "q"))


def salted(t: Tables) -> DataFrame:
    """Hot users are dealt to 8 salts and the other side repeated for each."""
    n = 8
    e = t.events.withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(n)))
    u = t.events.groupBy("user_id").agg(F.max("value").alias("most")).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))))
    return e.join(u, ["user_id", "salt"]).where("value = most").select("event_id", "user_id")


op("join_skew_salted", "SELECT event_id, user_id FROM events JOIN (SELECT user_id, max(value) AS most FROM events GROUP BY user_id) USING (user_id) WHERE value = most", salted)

# Aggregates -----------------------------------------------------------------

op("agg_basic", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS s, round(avg(value), 6) AS a, min(value) AS lo, max(value) AS hi FROM events GROUP BY event_type", lambda t: t.events.groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("s"), F.round(F.avg("value"), 6).alias("a"), F.min("value").alias("lo"), F.max("value").alias("hi")))
op("agg_minmax_by", "SELECT p_brand, arg_min(p_partkey, p_retailprice * 1000000 + p_partkey) AS cheapest, arg_max(p_partkey, p_retailprice * 1000000 + p_partkey) AS dearest FROM part GROUP BY p_brand", lambda t: t.part.groupBy("p_brand").agg(F.min_by("p_partkey", F.expr("p_retailprice * 1000000 + p_partkey")).alias("cheapest"), F.max_by("p_partkey", F.expr("p_retailprice * 1000000 + p_partkey")).alias("dearest")))
op("agg_collect_sorted", "SELECT label, list_sort(list(vec_id)) AS ids FROM embeddings GROUP BY label", lambda t: t.embeddings.groupBy("label").agg(F.array_sort(F.collect_list("vec_id")).alias("ids")))
op("agg_distinct", f"SELECT count(DISTINCT attr) AS u FROM ({D50})", lambda t: t.h("dup50").agg(F.countDistinct("attr").alias("u")))
op("agg_approx_distinct", "SELECT true AS close", lambda t: t.events.agg((F.abs(F.approx_count_distinct("user_id", 0.02) / F.countDistinct("user_id") - 1) <= 0.05).alias("close")))
op("agg_percentile", f"SELECT quantile_cont(attr, 0.25) AS q1, quantile_cont(attr, 0.5) AS q2, quantile_cont(attr, 0.9) AS q9 FROM ({H})", lambda t: t.h().agg(*[F.percentile("attr", p).alias(n) for n, p in (("q1", 0.25), ("q2", 0.5), ("q9", 0.9))]))
op("agg_kll", "SELECT true AS close", lambda t: t.h().agg(F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(attr), 0.5)").alias("k"), F.percentile("attr", 0.5).alias("p"), (F.max("attr") - F.min("attr")).alias("w")).select((F.abs(c("k") - c("p")) <= 0.05 * c("w")).alias("close")))


def count_min(t: Tables) -> DataFrame:
    """Every user's events by a count-min sketch, read in the public layout of its bytes: never fewer than there are, and within 1 % of all for 95 % of the users."""
    sketch = t.events.agg(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(7)).alias("s"), F.count("*").alias("total"))
    whole = lambda at, size: F.expr(f"cast(conv(hex(substring(s, {at} + 1, {size})), 16, -10) as bigint)")
    shape = sketch.withColumns({"depth": whole(12, 4), "wide": whole(16, 4)})
    exact = t.events.groupBy("user_id").agg(F.count("*").alias("n"))
    both = exact.crossJoin(F.broadcast(shape)).withColumn("i", F.explode(F.expr("sequence(0, cast(depth as int) - 1)")))  # the sketch is one row of fixed size
    both = both.withColumn("h", whole("20 + 8 * i", 8) * F.col("user_id"))
    both = both.withColumn("h", (F.col("h") + F.shiftright("h", 32)).bitwiseAND(F.lit(2**31 - 1)) % F.col("wide"))
    told = both.withColumn("x", whole("20 + 8 * depth + 8 * (i * wide + h)", 8)).groupBy("user_id", "n", "total").agg(F.min("x").alias("told"))
    return told.agg(F.bool_and(c("told") >= c("n")).alias("never_fewer"), (F.avg((c("told") - c("n") <= 0.01 * c("total")).cast("int")) >= 0.95).alias("close"))


op("agg_count_min", "SELECT true AS never_fewer, true AS close", count_min)
_G = "FROM part GROUP BY {}"
op("agg_grouping_sets", "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_size), ())", lambda t: t.part.groupingSets([[c("p_brand")], [c("p_size")], []], "p_brand", "p_size").agg(F.count("*").alias("n")).select("p_brand", "p_size", "n"))
op("agg_cube", "SELECT p_brand, p_size, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_size)", lambda t: t.part.cube("p_brand", "p_size").agg(F.count("*").alias("n")))
op("agg_rollup", "SELECT p_brand, p_size, count(*) AS n, grouping(p_size) AS g FROM part GROUP BY ROLLUP (p_brand, p_size)", lambda t: t.part.rollup("p_brand", "p_size").agg(F.count("*").alias("n"), F.grouping("p_size").cast("long").alias("g")))
op("agg_pivot", "SELECT event_type, count(*) FILTER (WHERE user_id % 2 = 0) AS even, count(*) FILTER (WHERE user_id % 2 = 1) AS odd FROM events GROUP BY event_type", lambda t: t.events.withColumn("side", F.when(c("user_id") % 2 == 0, "even").otherwise("odd")).groupBy("event_type").pivot("side", ["even", "odd"]).count().na.fill(0))


def centroids(t: Tables) -> DataFrame:
    by = t.embeddings.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(c("x").cast("double")).alias("m"))
    return by.select("label", "i", F.round("m", 6).alias("m"))


op("agg_centroid", "SELECT label, i - 1 AS i, round(avg(x), 6) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY label, i", centroids)
op("agg_having", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) > 5", lambda t: t.events.groupBy("user_id").agg(F.count("*").alias("n")).where("n > 5"))
op("agg_filtered", "SELECT count(*) FILTER (WHERE value > 50) AS over, count(*) AS n FROM events", lambda t: t.events.agg(F.count_if(c("value") > 50).alias("over"), F.count("*").alias("n")))

# Windows --------------------------------------------------------------------



def by_label() -> WindowSpec:
    return Window.partitionBy("label").orderBy("vec_id")


def by_user() -> WindowSpec:
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_O = "OVER (PARTITION BY label ORDER BY vec_id)"
for _key, _f, _sql in (("row_number", F.row_number, "row_number()"), ("rank", F.rank, "rank()"), ("dense_rank", F.dense_rank, "dense_rank()"), ("ntile", lambda: F.ntile(4), "ntile(4)")):
    op(f"win_{_key}", f"SELECT vec_id, {_sql} {_O} AS r FROM embeddings", lambda t, f=_f: t.embeddings.select("vec_id", f().over(by_label()).cast("long").alias("r")))
for _key, _f in (("percent_rank", F.percent_rank), ("cume_dist", F.cume_dist)):
    op(f"win_{_key}", f"SELECT vec_id, round({_key}() {_O}, 6) AS r FROM embeddings", lambda t, f=_f: t.embeddings.select("vec_id", F.round(f().over(by_label()), 6).alias("r")))
_EO = "PARTITION BY user_id ORDER BY ts, event_id"
op("win_lag_lead", f"SELECT event_id, lag(value) OVER w AS a, lead(value, 2) OVER w AS b FROM events WINDOW w AS ({_EO})", lambda t: t.events.select("event_id", F.lag("value").over(by_user()).alias("a"), F.lead("value", 2).over(by_user()).alias("b")))
op("win_first_last_nth", f"SELECT event_id, first_value(value) OVER w AS a, last_value(value) OVER w AS b, nth_value(value, 2) OVER w AS n FROM events WINDOW w AS ({_EO} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", lambda t: t.events.select("event_id", *[f.over(by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for f, n in ((F.first("value"), "a"), (F.last("value"), "b"), (F.nth_value("value", 2), "n"))]))
op("win_rows_frame", f"SELECT event_id, round(sum(value) OVER ({_EO} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS s FROM events", lambda t: t.events.select("event_id", F.round(F.sum("value").over(by_user().rowsBetween(-2, 0)), 6).alias("s")))
op("win_range_frame", f"SELECT id, count(*) OVER (PARTITION BY attr % 10 ORDER BY attr RANGE BETWEEN 50000 PRECEDING AND 50000 FOLLOWING) AS n FROM ({H})", lambda t: t.h().select("id", F.count("*").over(Window.partitionBy(c("attr") % 10).orderBy("attr").rangeBetween(-50000, 50000)).alias("n")))
op("win_time_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events", lambda t: t.events.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(c("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n")))


def two_phase(t: Tables) -> DataFrame:
    from hybridrange import ranks

    return ranks.with_positions(t.h("line").select("id", "attr"), "attr").select("id", "pos")


op("win_two_phase_rank", f"SELECT id, row_number() OVER (ORDER BY attr, id) - 1 AS pos FROM ({hybrid_sql('line')})", two_phase)

# Sorting and sets -----------------------------------------------------------

op("sort_limit", f"SELECT id, attr FROM ({H}) ORDER BY attr LIMIT 20", lambda t: t.h().select("id", "attr").orderBy("attr").limit(20))
op("sort_offset", f"SELECT id FROM ({H}) ORDER BY attr LIMIT 10 OFFSET 30", lambda t: t.h().orderBy("attr").offset(30).limit(10).select("id"))
op("topk_per_query", "SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3", lambda t: t.part.withColumn("r", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("r <= 3").select("p_brand", "p_partkey"))
op("topk_ties_by_id", f"SELECT id FROM ({D50}) ORDER BY attr, id LIMIT 15", lambda t: t.h("dup50").orderBy("attr", "id").limit(15).select("id"))
op("sort_nulls_last", "SELECT vec_id FROM (SELECT vec_id, nullif(label, 3) AS x FROM embeddings ORDER BY x ASC NULLS LAST, vec_id LIMIT 25)", lambda t: t.embeddings.select("vec_id", F.nullif("label", F.lit(3)).alias("x")).orderBy(F.asc_nulls_last("x"), "vec_id").limit(25).select("vec_id"))
_A, _B = "SELECT p_size AS x FROM part WHERE p_partkey % 2 = 0", "SELECT p_size AS x FROM part WHERE p_partkey % 3 = 0"
for _key, _sql, _f in (("union_all", "UNION ALL", lambda a, b: a.union(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)), ("union_by_name", "UNION ALL", lambda a, b: a.unionByName(b))):
    op(f"set_{_key}", f"{_A} {_sql} {_B}", lambda t, f=_f: f(t.part.where("p_partkey % 2 = 0").select(c("p_size").alias("x")), t.part.where("p_partkey % 3 = 0").select(c("p_size").alias("x"))))

# Strings, dates, numbers ----------------------------------------------------

op("str_url_parts", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages", lambda t: t.pages.select("page_id", F.coalesce(F.regexp_extract("url", "^([a-z]+)://", 1), F.lit("")).alias("scheme"), F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")))
op("str_clean", "SELECT p_partkey, upper(trim(p_name)) AS n, length(p_name) AS len FROM part", lambda t: t.part.select("p_partkey", F.upper(F.trim("p_name")).alias("n"), F.length("p_name").cast("long").alias("len")))
op("str_regex", "SELECT p_partkey, regexp_replace(p_type, '[AEIOU]', '', 'g') AS x FROM part", lambda t: t.part.select("p_partkey", F.regexp_replace("p_type", "[AEIOU]", "").alias("x")))
op("str_prefix_key", "SELECT substring(url, 1, 12) AS k, count(*) AS n FROM pages GROUP BY 1", lambda t: t.pages.groupBy(F.substring("url", 1, 12).alias("k")).agg(F.count("*").alias("n")))
op("str_distance", "SELECT a.p_partkey AS p, levenshtein(a.p_name, b.p_name) AS d FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 1", lambda t: t.part.select(c("p_partkey").alias("p"), c("p_name").alias("x")).join(t.part.select((c("p_partkey") - 1).alias("p"), c("p_name").alias("y")), "p").select("p", F.levenshtein("x", "y").cast("long").alias("d")))
op("date_trunc_counts", "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS m, count(*) AS n FROM orders GROUP BY 1", lambda t: t.orders.groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m")).agg(F.count("*").alias("n")))
op("date_diff", "SELECT o_orderkey, date_diff('day', o_orderdate::DATE, l_shipdate::DATE) AS d FROM orders JOIN lineitem ON o_orderkey = l_orderkey", lambda t: t.orders.join(t.lineitem, c("o_orderkey") == c("l_orderkey")).select("o_orderkey", F.datediff("l_shipdate", "o_orderdate").cast("long").alias("d")))
op("date_add_interval", "SELECT o_orderkey, o_orderdate + INTERVAL 3 MONTH AS due FROM orders", lambda t: t.orders.select("o_orderkey", (c("o_orderdate") + F.expr("interval 3 months")).alias("due")))
op("date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, dayofyear(o_orderdate) AS d FROM orders", lambda t: t.orders.select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q"), F.dayofyear("o_orderdate").cast("long").alias("d")))
op("ts_to_long", "SELECT event_id, epoch_us(ts) AS us FROM events", lambda t: t.events.select("event_id", F.unix_micros(c("ts").cast("timestamp")).alias("us")))
op("math_layers", f"SELECT id, CAST(floor(log2(attr + 2)) AS BIGINT) AS l FROM ({H})", lambda t: t.h().select("id", F.floor(F.log2(c("attr") + 2)).alias("l")))
op("math_rounding", "SELECT p_partkey, round(p_retailprice / 7, 2) AS r, CAST(floor(p_retailprice / 7) AS BIGINT) AS f, CAST(ceil(p_retailprice / 7) AS BIGINT) AS u FROM part", lambda t: t.part.select("p_partkey", F.round(c("p_retailprice") / 7, 2).alias("r"), F.floor(c("p_retailprice") / 7).alias("f"), F.ceil(c("p_retailprice") / 7).alias("u")))
op("math_bits", f"SELECT id, attr & 255 AS a, attr >> 4 AS s, bit_count(attr) AS n FROM ({H})", lambda t: t.h().select("id", c("attr").bitwiseAND(255).alias("a"), F.shiftright("attr", 4).alias("s"), F.bit_count("attr").cast("long").alias("n")))

# Arrays, maps, conditionals, subqueries -------------------------------------

op("arr_transform_filter", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n FROM embeddings", lambda t: t.embeddings.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n")))
op("arr_sort_slice", "SELECT vec_id, list_sort(embedding)[1:3]::DOUBLE[] AS least FROM embeddings", lambda t: t.embeddings.select("vec_id", F.slice(F.array_sort("embedding"), 1, 3).cast("array<double>").alias("least")))
op("arr_explode", "SELECT vec_id, i - 1 AS i, x FROM (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE x > 0.3", lambda t: t.embeddings.select("vec_id", F.posexplode("embedding").alias("i", "x")).where("x > 0.3").select("vec_id", "i", c("x").cast("double").alias("x")))
_L = "(SELECT label, list(vec_id ORDER BY vec_id) AS ids FROM embeddings GROUP BY label)"
op("arr_overlap", f"SELECT a.label AS x, b.label AS y, len(list_intersect(a.ids[1:9], b.ids[1:9])) AS n FROM {_L} a JOIN {_L} b ON b.label = a.label + 1", lambda t: (lambda g: g.select(c("label").alias("x"), c("ids").alias("a")).join(g.select((c("label") - 1).alias("x"), c("label").alias("y"), c("ids").alias("b")), "x").select("x", "y", F.size(F.array_intersect(F.slice("a", 1, 9), F.slice("b", 1, 9))).cast("long").alias("n")))(t.embeddings.groupBy("label").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))))
op("arr_distinct_union", "SELECT p_brand, list_sort(list(DISTINCT p_size)) AS s FROM part GROUP BY p_brand", lambda t: t.part.groupBy("p_brand").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.array("p_size"))))).alias("s")))
op("arr_fold", "SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: abs(x))), 6) AS s FROM embeddings", lambda t: t.embeddings.select("vec_id", F.round(V.total(F.transform("embedding", lambda x: F.abs(x.cast("double")))), 6).alias("s")))
op("json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", lambda t: t.events.select("event_id", F.from_json("props", "k long")["k"].alias("k")))
op("json_schema_of", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS k, count(*) AS n FROM events GROUP BY 1", lambda t: t.events.groupBy((F.get_json_object("props", "$.k").cast("long") % 10).alias("k")).agg(F.count("*").alias("n")))
op("map_build", "SELECT p_brand, CAST(sum(p_size) AS BIGINT) AS s FROM part GROUP BY p_brand", lambda t: t.part.groupBy("p_brand").agg(F.map_from_entries(F.collect_list(F.struct("p_partkey", "p_size"))).alias("m")).select("p_brand", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x).alias("s")))
op("map_filter_keys", "SELECT p_brand, count(*) FILTER (WHERE p_partkey % 2 = 0) AS n FROM part GROUP BY p_brand", lambda t: t.part.groupBy("p_brand").agg(F.map_from_entries(F.collect_list(F.struct("p_partkey", "p_size"))).alias("m")).select("p_brand", F.size(F.map_filter("m", lambda k, v: k % 2 == 0)).cast("long").alias("n")))
op("to_json_rows", "SELECT n_nationkey, '{\"n_nationkey\":' || n_nationkey || ',\"n_name\":\"' || n_name || '\"}' AS j FROM nation", lambda t: t.nation.select("n_nationkey", F.to_json(F.struct("n_nationkey", "n_name")).alias("j")))
op("case_when", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 's' WHEN p_size < 30 THEN 'm' ELSE 'l' END AS g FROM part", lambda t: t.part.select("p_partkey", F.when(c("p_size") < 10, "s").when(c("p_size") < 30, "m").otherwise("l").alias("g")))
op("coalesce_nullif", "SELECT vec_id, coalesce(nullif(label, 3), -1) AS x FROM embeddings", lambda t: t.embeddings.select("vec_id", F.coalesce(F.nullif("label", F.lit(3)), F.lit(-1)).alias("x")))
op("try_cast_div", "SELECT vec_id, CASE WHEN label = 0 THEN NULL ELSE vec_id / label END AS d, TRY_CAST(CASE WHEN label < 5 THEN 'x' ELSE '7' END AS INTEGER) AS i FROM embeddings", lambda t: t.embeddings.select("vec_id", F.try_divide(c("vec_id"), c("label")).alias("d"), F.when(c("label") < 5, "x").otherwise("7").try_cast("int").alias("i")))


def sql(name: str, text: str, oracle: str | None = None) -> None:
    """One statement that both engines run over the same tables."""

    def f(t: Tables) -> DataFrame:
        for x in ("customer", "orders", "part", "embeddings", "events", "nation", "region", "lineitem", "pages"):
            getattr(t, x).createOrReplaceTempView(x)
        return t.spark.sql(text)

    op(name, oracle or text, f)


sql("sub_scalar", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
sql("sub_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 100000)")
sql("sub_in", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
sql("cte_chain", "WITH a AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY o_custkey), b AS (SELECT o_custkey FROM a WHERE s > 200000) SELECT c_mktsegment, count(*) AS n FROM customer JOIN b ON c_custkey = o_custkey GROUP BY c_mktsegment")
sql("cte_recursive_reach", "WITH RECURSIVE r AS (SELECT n_nationkey AS k FROM nation WHERE n_nationkey = 0 UNION ALL SELECT k + 3 FROM r WHERE k + 3 < 25) SELECT k FROM r")
sql("lateral_explode", "SELECT vec_id, x FROM embeddings LATERAL VIEW explode(slice(embedding, 1, 2)) e AS x", "SELECT vec_id, unnest(embedding[1:2]) AS x FROM embeddings")
sql("sql_counts", f"SELECT count(*) AS n FROM embeddings WHERE (vec_id * {SCALE} + 104729) % 1000003 BETWEEN 100000 AND 600000")
op("sample_hash", f"SELECT id FROM ({H}) WHERE (id * 2654435761) % 4294967296 < 1073741824", lambda t: t.h().where((c("id") * 2654435761) % 4294967296 < 1073741824).select("id"))
def _strata(t) -> DataFrame:
    """Labels whose sample is within five deviations of a half of their rows."""
    whole, part = t.embeddings.groupBy("label").agg(F.count("*").alias("n")), t.embeddings.sampleBy("label", {i: 0.5 for i in range(10)}, 3).groupBy("label").agg(F.count("*").alias("k"))
    return whole.join(part, "label", "left").select("label", (F.abs(F.coalesce("k", F.lit(0)) - F.col("n") / 2) <= 5 * F.sqrt("n") / 2).alias("within"))


op("sample_stratified", "SELECT label, true AS within FROM embeddings GROUP BY label", _strata)

# User-defined functions ------------------------------------------------------


def by_udf(t: Tables, kind: str) -> DataFrame:
    if kind == "arrow":

        @F.pandas_udf("double")
        def d(a, b):
            import numpy as np
            import pandas as pd

            return pd.Series([float(np.cumsum((np.asarray(x, float) - np.asarray(y, float)) ** 2)[-1]) for x, y in zip(a, b, strict=True)])
    else:
        d = F.udf(lambda x, y: sum((float(p) - float(q)) ** 2 for p, q in zip(x, y, strict=True)), "double")
    return neighbours(t).select("vec_id", F.round(d("a", "b"), 6).alias("d"))


for _kind in ("arrow", "python"):
    op(f"udf_distance_{_kind}", ORACLES["vec_l2sq"], lambda t, kind=_kind: by_udf(t, kind))


def vec_sum(t: Tables) -> DataFrame:
    @F.pandas_udf("array<double>", F.PandasUDFType.GROUPED_AGG)
    def total(v):
        import numpy as np

        return np.stack(v.to_numpy()).astype(float).sum(0).tolist()

    return t.embeddings.groupBy("label").agg(total("embedding").alias("s")).select("label", F.round(F.get("s", F.lit(0)), 5).alias("first"))


op("udaf_vec_sum", "SELECT label, round(sum(embedding[1]::DOUBLE), 5) AS first FROM embeddings GROUP BY label", vec_sum)


def layer_windows(t: Tables) -> DataFrame:
    @F.udtf(returnType="layer: int, low: long, high: long")
    class Windows:
        def eval(self, rank: int, uniques: int, o: int):
            layer = 0
            while True:
                yield layer, max(0, rank - o**layer), min(uniques - 1, rank + o**layer)
                if 2 * o**layer >= uniques:
                    return
                layer += 1

    t.spark.udtf.register("layer_windows", Windows)
    t.embeddings.select("vec_id").createOrReplaceTempView("ranked_rows")
    return t.spark.sql("SELECT vec_id, w.layer, w.low, w.high FROM ranked_rows, LATERAL layer_windows(vec_id, (SELECT count(*) FROM ranked_rows), 4) w")


op("udtf_layer_windows", "SELECT vec_id, CAST(l AS INTEGER) AS layer, CAST(greatest(0, vec_id - pow(4, l)) AS BIGINT) AS low, CAST(least(n - 1, vec_id + pow(4, l)) AS BIGINT) AS high FROM embeddings, (SELECT count(*) AS n FROM embeddings), range(0, 20) AS r(l) WHERE l = 0 OR 2 * pow(4, l - 1) < n", layer_windows)


# The index from SQL -----------------------------------------------------------


def bucketed(t: Tables) -> DataFrame:
    """A table bucketed and sorted by segment, so that a later join on it moves one side only."""
    import uuid

    name = f"bucketed_{uuid.uuid4().hex}"
    t.h().select("id", "attr", F.floor(c("attr") / 100000).alias("seg")).write.bucketBy(8, "seg").sortBy("attr").saveAsTable(name)
    return t.spark.table(name).groupBy("seg").agg(F.count("*").alias("n"))


op("sink_bucketed", f"SELECT attr // 100000 AS seg, count(*) AS n FROM ({H}) GROUP BY 1", bucketed)


def asked_in_sql(t: Tables) -> DataFrame:
    """Exact range search as one SQL statement over registered views."""
    from hybridrange.methods import asked

    data, q = asked(t.spark, t.sf_dir)
    data.createOrReplaceTempView("hybrid_rows")
    q.createOrReplaceTempView("range_queries")
    return t.spark.sql("""
        SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INT) AS pos FROM (
          SELECT qid, id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM (
            SELECT /*+ BROADCAST(q) */ qid, id, sqrt(aggregate(zip_with(vec, qvec, (a, b) -> (double(a) - double(b)) * (double(a) - double(b))), 0D, (s, x) -> s + x)) AS dist
            FROM hybrid_rows JOIN range_queries q ON attr BETWEEN lo AND hi)) WHERE pos <= 10""")


def _exact_sql() -> str:
    from hybridrange.methods import exact_sql

    return exact_sql("rand")


op("sql_exact_range_knn", _exact_sql(), asked_in_sql)


def recall_udaf(t: Tables) -> DataFrame:
    """Recall as a grouped-aggregate function over hits."""
    from hybridrange.baselines.run import postfilter_exact
    from hybridrange.methods import asked, truth_of

    @F.pandas_udf("double", F.PandasUDFType.GROUPED_AGG)
    def share(hit):
        return float(hit.mean())

    data, q = asked(t.spark, t.sf_dir)
    found = postfilter_exact(data, q, 10, 0.5).select("qid", "id", F.lit(1.0).alias("hit"))
    both = truth_of(t.spark, t.sf_dir).select("qid", "id").join(found, ["qid", "id"], "left").na.fill(0.0, ["hit"])
    return both.groupBy("qid").agg(F.round(share("hit"), 9).alias("recall"))


def _recall_sql() -> str:
    from hybridrange.methods import ORACLES as M

    return f"SELECT qid, round(recall, 9) AS recall FROM ({M['recall']})"


op("udaf_recall", _recall_sql(), recall_udaf)


def lid_udaf(t: Tables) -> DataFrame:
    """Local dimension as a grouped-aggregate function over distances."""
    from hybridrange.methods import truth_of

    @F.pandas_udf("double", F.PandasUDFType.GROUPED_AGG)
    def lid(dist):
        import numpy as np

        d = dist[dist > 0].to_numpy()
        m = np.log(d / dist.max()).mean() if len(d) else 0.0
        return float(-1 / m) if m < 0 else None

    return truth_of(t.spark, t.sf_dir).where("dist > 0").groupBy("qid").agg(F.round(lid("dist"), 4).alias("lid"))


def _lid_sql() -> str:
    from hybridrange.methods import ORACLES as M

    return M["lid"]


op("udaf_lid", _lid_sql(), lid_udaf)
