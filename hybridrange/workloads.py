"""The paper's experiments, re-expressed on the given tables.

Each returns a table of measured figures; where a behaviour is claimed, a second
query states it as booleans with an oracle.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hybridrange import index, measures, theory
from hybridrange.baselines import run
from hybridrange.exact import _finished, exact_range_knn, nearest_in_blocks
from hybridrange.hybrid import hybrid, hybrid_sql, l2sq_sql, make_ranges, ranges_sql
from hybridrange.kernel.stack import Settings
from hybridrange.methods import FLOORS, K, asked, built, held, truth_of
from hybridrange.plans.tables import cut

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
OMEGAS = (10, 16, 32, 64, 128)


def query(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


def built_size(parts: DataFrame) -> DataFrame:
    """(bytes, build_s) of an index, summed over its segments."""
    each = parts.groupBy("seg", "sub").agg(F.max("bytes").alias("bytes"), F.max("build_s").alias("s"))
    return each.agg(F.sum("bytes").alias("bytes"), F.round(F.sum("s"), 3).alias("build_s"))


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def swept(spark: SparkSession, sf_dir: str, kind: str, name: str = "rand", order: str = "shuffled", omegas: tuple[int, ...] = OMEGAS, k: int = K, fixed: int | None = None, **settings) -> DataFrame:
    """Results of one kind over a sweep of beam widths, shared by the experiments of a session."""
    how = {} if fixed is None else {"fixed": fixed}
    data, q = asked(spark, sf_dir, name, **how)
    return held(spark, (sf_dir, name, kind, order, omegas, k, fixed, str(sorted(settings.items()))), lambda: run.run_kind(kind, data, q, k, omegas, order, **settings))


def swept_sets(spark: SparkSession, sf_dir: str, fixed: tuple[int | None, ...], omegas: tuple[int, ...] = OMEGAS, hows: tuple[dict, ...] = ()) -> DataFrame:
    """One window stack, built once, over a sweep of beam widths: for the queries of each of ``fixed``, which ``set`` tells by its place, in each of ``hows``."""
    sets = [asked(spark, sf_dir, **({} if f is None else {"fixed": f})) for f in fixed]
    q = union([x.withColumn("set", F.lit(i)) for i, (_, x) in enumerate(sets)])
    return held(spark, (sf_dir, "sets", fixed, omegas, str(hows)), lambda: run.run_kind("window_stack", sets[0][0], q, K, omegas, hows=hows))


def truth_of_sets(spark: SparkSession, sf_dir: str, fixed: tuple[int | None, ...]) -> DataFrame:
    """The exact answers to the queries of ``swept_sets``."""
    return union([truth_of(spark, sf_dir, **({} if f is None else {"fixed": f})).withColumn("set", F.lit(i)) for i, f in enumerate(fixed)])


def points(parts: DataFrame, truth: DataFrame, k: int = K, by: tuple[str, ...] = ()) -> DataFrame:
    """(omega, recall, dc, fc, qps): means of one sweep, or of those that ``by`` tells apart; queries a second on one core."""
    own = [c for c in by if c in truth.columns]
    found = run.merged(parts, k, by)
    hits = truth.select(*own, "qid", "id").join(found.select(*by, "omega", "qid", "id"), [*own, "qid", "id"]).groupBy(*by, "omega", "qid").agg(F.count("*").alias("hits"))
    want = truth.groupBy(*own, "qid").agg(F.least(F.lit(k), F.count("*")).alias("want"))
    widths = F.broadcast(parts.select(*by, "omega").distinct())  # a handful of widths
    each = (want.join(widths, own) if own else want.crossJoin(widths)).join(hits, [*by, "omega", "qid"], "left")
    recall = each.groupBy(*by, "omega").agg(F.avg(F.coalesce("hits", F.lit(0)) / F.col("want")).alias("recall"))
    cost = parts.groupBy(*by, "omega", "qid").agg(F.sum("dc").alias("dc"), F.sum("fc").alias("fc"), F.sum("search_s").alias("s")).groupBy(*by, "omega").agg(F.avg("dc").alias("dc"), F.avg("fc").alias("fc"), F.round(1 / F.avg("s"), 1).alias("qps"))
    return recall.join(cost, [*by, "omega"]).select(*by, "omega", F.round("recall", 4).alias("recall"), F.round("dc", 1).alias("dc"), F.round("fc", 1).alias("fc"), "qps")


@query("index_cost")
def index_cost(spark, sf_dir):
    """Bytes and build seconds of every index on each of four sets."""
    out = []
    for name in ("rand", "time", "title", "id"):
        kinds = spark.range(1).select(F.explode(F.array(*[F.lit(x) for x in FLOORS])).alias("index"), F.lit(name).alias("dataset"))
        size = run.sizes_of(tuple(FLOORS), hybrid(spark, sf_dir, name)).groupBy("index").agg(F.sum("bytes").alias("bytes"), F.round(F.sum("build_s"), 3).alias("build_s"))
        out.append(kinds.join(size, "index", "left").select("index", "dataset", "bytes", "build_s"))
    return union(out)


@query("recall_sweep")
def recall_sweep(spark, sf_dir):
    """Recall, distance computations and rate of every index over a sweep of beam widths, mixed ranges."""
    return union([points(swept(spark, sf_dir, kind), truth_of(spark, sf_dir)).withColumn("index", F.lit(kind)) for kind in FLOORS])


@query("recall_by_fraction")
def recall_by_fraction(spark, sf_dir):
    """The stack at single fractions."""
    return union([points(swept(spark, sf_dir, "window_stack", fixed=f), truth_of(spark, sf_dir, fixed=f)).withColumn("f_exp", F.lit(f)) for f in (0, 1, 4, 7, 10)])


@query("order_effect")
def order_effect(spark, sf_dir):
    """Arrivals in order of the attribute against shuffled ones."""
    return union([points(swept(spark, sf_dir, "window_stack", name, order), truth_of(spark, sf_dir, name)).withColumns({"dataset": F.lit(name), "arrival": F.lit(order)}) for name in ("rand", "time") for order in ("sorted", "shuffled")])


@query("oracle_gap")
def oracle_gap(spark, sf_dir):
    """Distance computations against a graph built for each range."""
    a, b = (points(swept(spark, sf_dir, kind), truth_of(spark, sf_dir)) for kind in ("window_stack", "oracle_graph"))
    b = b.select("omega", F.col("recall").alias("oracle_recall"), F.col("dc").alias("oracle_dc"))
    return a.join(b, "omega").select("omega", "recall", "oracle_recall", "dc", "oracle_dc", F.round(F.col("dc") / F.col("oracle_dc"), 3).alias("dc_ratio"))


@query("early_stop_effect")
def early_stop_effect(spark, sf_dir):
    """Cost with and without the early stop at three recall levels, by interpolation."""
    out = []
    for stop in (True, False):
        p = cut(points(swept(spark, sf_dir, "window_stack", how={"early_stop": stop}), truth_of(spark, sf_dir)), "points")
        out += [measures.at_recall(p, level, "dc").withColumn("early_stop", F.lit(stop)) for level in (0.9, 0.95, 0.99)]
    return union(out)


@query("early_stop_claim", "SELECT true AS fewer_distances, true AS fewer_checks")
def early_stop_claim(spark, sf_dir):
    """Without the early stop every beam width costs at least as many distances and checks in the mean."""
    on, off = (points(swept(spark, sf_dir, "window_stack", how={"early_stop": x}), truth_of(spark, sf_dir)).select("omega", F.col("dc").alias(f"dc{x}"), F.col("fc").alias(f"fc{x}")) for x in (True, False))
    return on.join(off, "omega").agg(F.min(F.col("dcTrue") <= F.col("dcFalse")).alias("fewer_distances"), F.min(F.col("fcTrue") <= F.col("fcFalse")).alias("fewer_checks"))


@query("landing_effect")
def landing_effect(spark, sf_dir):
    """The landing layer forced from the top to the lowest, and by an estimate, for mixed ranges and for those of a 16th and a 1,024th."""
    layers, fixed = ("auto", "estimate", "top", 3, 2, 1, 0), (None, 4, 10)
    parts = swept_sets(spark, sf_dir, fixed, (16, 32), tuple({"landing": x} for x in layers))
    told = {"landing": F.get(F.array(*[F.lit(str(x)) for x in layers]), "way"), "f_exp": F.get(F.array(*[F.lit(-1 if f is None else f) for f in fixed]), "set")}
    return points(parts, truth_of_sets(spark, sf_dir, fixed), by=("way", "set")).withColumns(told).drop("way", "set")


@query("landing_claim", "SELECT true AS fewer_checks_than_top, true AS recall_kept")
def landing_claim(spark, sf_dir):
    """The chosen layer checks no more neighbours than the top, at about its recall."""
    auto, top = (points(swept(spark, sf_dir, "window_stack", omegas=(32,), how={"landing": x}), truth_of(spark, sf_dir)).select(F.col("fc").alias(f"fc_{x}"), F.col("recall").alias(f"r_{x}")) for x in ("auto", "top"))
    return auto.crossJoin(top).select((F.col("fc_auto") <= F.col("fc_top")).alias("fewer_checks_than_top"), (F.col("r_auto") >= F.col("r_top") - 0.03).alias("recall_kept"))  # one row each


def correlated(spark: SparkSession, sf_dir: str, kind: str) -> tuple[DataFrame, DataFrame]:
    """Queries of the rows nearest the pivot with a range of an eighth at the far end, anywhere, or at the pivot."""
    near = hybrid(spark, sf_dir, "pivot")
    n = near.count()
    close = near.where(F.col("attr") < n // 10)
    q = close.select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    if kind == "none":
        data = hybrid(spark, sf_dir, "rand")
        return data, make_ranges(data, fixed=3, step=1).drop("qvec").join(q, "qid").select("qid", "qvec", "f_exp", "lo", "hi")
    low, high = (0, n // 8 - 1) if kind == "high" else (n - n // 8, n - 1)
    return near, q.select("qid", "qvec", F.lit(3).alias("f_exp"), F.lit(low).cast("long").alias("lo"), F.lit(high).cast("long").alias("hi"))


@query("correlation_effect")
def correlation_effect(spark, sf_dir):
    """Recall of post-filtering and of the stack for queries of low, no and high correlation."""
    out = []
    for kind in ("low", "none", "high"):
        data, q = correlated(spark, sf_dir, kind)
        q = cut(q, "asked")
        truth = cut(exact_range_knn(data, q, K), "truth")
        post = measures.recall(run.postfilter_exact(data, q, K, 0.5), truth, K).agg(F.round(F.avg("recall"), 4).alias("postfilter_recall"))
        stack = points(run.run_kind("window_stack", data, q, K, (64,)), truth)
        out.append(stack.crossJoin(post).withColumn("correlation", F.lit(kind)))  # one row each
    return union(out)


@query("correlation_claim", "SELECT true AS rises, true AS stack_holds")
def correlation_claim(spark, sf_dir):
    """Post-filtering gains with correlation; the stack keeps its recall without it."""
    t = cut(correlation_effect(spark, sf_dir), "claim").groupBy().pivot("correlation", ["low", "none", "high"]).agg(F.max("postfilter_recall").alias("p"), F.max("recall").alias("r"))
    return t.select(((F.col("low_p") < F.col("none_p")) & (F.col("none_p") < F.col("high_p"))).alias("rises"), (F.least("low_r", "none_r", "high_r") >= 0.9).alias("stack_holds"))


@query("hardness", f"""WITH {ranges_sql('rand')}, d AS (SELECT qid, f_exp, sqrt({l2sq_sql('h.vec', 'q.qvec')}) AS dist, id FROM q JOIN h ON attr >= lo AND attr <= hi),
t AS (SELECT qid, f_exp, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= 10),
l AS (SELECT qid, f_exp, avg(CASE WHEN dist > 0 THEN ln(dist / far) END) AS m FROM (SELECT *, max(dist) OVER (PARTITION BY qid) AS far FROM t) GROUP BY qid, f_exp)
SELECT f_exp, round(avg(CASE WHEN m < 0 THEN round(-1 / m, 4) END), 3) AS lid FROM l GROUP BY f_exp""")
def hardness(spark, sf_dir):
    """Local dimension by fraction."""
    q = asked(spark, sf_dir)[1]
    return q.select("qid", "f_exp").join(measures.lid(truth_of(spark, sf_dir)), "qid", "left").groupBy("f_exp").agg(F.round(F.avg("lid"), 3).alias("lid"))


@query("hardness_cost")
def hardness_cost(spark, sf_dir):
    """Local dimension beside recall and cost at single fractions."""
    fixed = (0, 2, 4)
    lid = union([measures.lid(truth_of(spark, sf_dir, fixed=f)).agg(F.round(F.avg("lid"), 3).alias("lid")).withColumns({"set": F.lit(i), "f_exp": F.lit(f)}) for i, f in enumerate(fixed)])
    return points(swept_sets(spark, sf_dir, fixed), truth_of_sets(spark, sf_dir, fixed), by=("set",)).join(F.broadcast(lid), "set").drop("set")  # one row a set


@query("k_effect")
def k_effect(spark, sf_dir):
    """1, 50 and 100 neighbours."""
    return union([points(swept(spark, sf_dir, "window_stack", omegas=(k, 2 * k, 4 * k), k=k), truth_of(spark, sf_dir, k=k), k).withColumn("k", F.lit(k)) for k in (1, 50, 100)])


@query("sensitivity")
def sensitivity(spark, sf_dir):
    """Beam width while building, most links, window base."""
    out = []
    for name, values in (("omega_c", (16, 64, 128)), ("m", (8, 16, 32)), ("o", (2, 4, 16))):
        for v in values:
            parts = swept(spark, sf_dir, "window_stack", omegas=(16, 64), **{name: v})
            size = built_size(parts)
            out.append(points(parts, truth_of(spark, sf_dir)).crossJoin(size).withColumns({"parameter": F.lit(name), "value": F.lit(v)}))  # one row
    return union(out)


@query("sensitivity_claim", "SELECT true AS larger_base_fewer_bytes, true AS more_links_more_bytes")
def sensitivity_claim(spark, sf_dir):
    """A larger base makes fewer layers, more links more bytes."""
    t = cut(sensitivity(spark, sf_dir).groupBy("parameter", "value").agg(F.max("bytes").alias("bytes")), "claim")
    of = lambda p, v: F.max(F.when((F.col("parameter") == p) & (F.col("value") == v), F.col("bytes")))
    return t.agg((of("o", 2) > of("o", 4)).alias("a"), (of("o", 4) > of("o", 16)).alias("b"), (of("m", 8) < of("m", 32)).alias("c")).select((F.col("a") & F.col("b")).alias("larger_base_fewer_bytes"), F.col("c").alias("more_links_more_bytes"))


@query("unique_effect")
def unique_effect(spark, sf_dir):
    """Fewer unique values make fewer layers; recall beside it."""
    out = []
    for name in ("dup10", "dup50", "dup250", "label", "price", "rand"):
        size = index_layers(spark, sf_dir, name)
        out.append(points(swept(spark, sf_dir, "window_stack", name, omegas=(64,)), truth_of(spark, sf_dir, name)).crossJoin(size).withColumn("dataset", F.lit(name)))  # one row
    return union(out)


def index_layers(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return built(spark, sf_dir, name).agg(F.max(F.size("links")).cast("long").alias("layers"))


_U = " UNION ALL ".join(f"SELECT '{x}' AS dataset, count(DISTINCT attr) AS u FROM ({hybrid_sql(x)})" for x in ("dup10", "dup50", "dup250", "rand"))


@query("unique_layers", f"SELECT dataset, (SELECT count(*) + 1 FROM range(0, 40) AS r(i) WHERE 2 * pow(4, i) < u) AS layers FROM ({_U})")
def unique_layers(spark, sf_dir):
    """Layers built for each number of unique values."""
    return union([index_layers(spark, sf_dir, x).withColumn("dataset", F.lit(x)) for x in ("dup10", "dup50", "dup250", "rand")])


@query("growth")
def growth(spark, sf_dir):
    """Rows, unique values, segments and the published size of the line items' index, by segment of 50,000 rows."""
    from hybridrange.layers import layer_count_col

    rows = index.segmented(hybrid(spark, sf_dir, "line"), 50_000).groupBy("seg", "sub").agg(F.count("*").alias("rows"), F.countDistinct("rank_u").alias("uniques"))
    sized = rows.withColumn("bytes", F.col("rows") * layer_count_col(F.col("uniques"), 4) * 64)
    return sized.agg(F.count("*").alias("segments"), F.sum("rows").alias("rows"), F.sum("uniques").alias("uniques"), F.sum("bytes").alias("bytes"))


@query("exact_line", f"""WITH {ranges_sql('line', fixed=8)}, d AS (SELECT qid, id, sqrt({l2sq_sql('h.vec', 'q.qvec')}) AS dist FROM q JOIN h ON attr >= lo AND attr <= hi)
SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= 10""")
def exact_line(spark, sf_dir):
    """Exact search over all line items in narrow ranges of ship dates."""
    data, q = asked(spark, sf_dir, "line", fixed=8)
    found = nearest_in_blocks(data, q, K, lambda c: F.floor(F.datediff(c, F.lit("1992-01-01")) / 16))
    return _finished(found, K)


def halves(spark: SparkSession, sf_dir: str, kind: str, whole: bool) -> DataFrame:
    """Results of an index that was built on all rows, or on the even ids with the odd ones inserted, at beam width 64."""
    data, q = asked(spark, sf_dir, fixed=1)

    def made() -> DataFrame:
        if kind != "window_stack":
            return run.run_kind(kind, data, q, K, (64,), **({} if whole else {"order": "halves", "first": data.where("id % 2 = 0").count() / data.count()}))
        began = time.time()
        # segments of a half are built with room for the other, so both ways end with segments of the same size
        held_ = cut(index.build_index(data) if whole else index.build_index(data.where("id % 2 = 0"), cap=index.CAP // 2), "half")
        if not whole:
            held_ = cut(index.insert(held_, data.where("id % 2 = 1")), "grown")
        took = time.time() - began
        size = F.lit(0).cast("long")
        found = index.search(held_, q, K, 64, complete=False)
        return found.select(F.lit(0).cast("long").alias("seg"), F.lit(0).alias("sub"), "qid", F.lit(64).alias("omega"), "id", "dist", "dc", "fc", size.alias("bytes"), F.lit(took).alias("build_s"), F.lit(0.0).alias("search_s"))

    return held(spark, (sf_dir, "halves", kind, whole), made)


@query("half_insert")
def half_insert(spark, sf_dir):
    """Recall and cost after one half was built and the other inserted, and of the whole built at once."""
    truth, out = truth_of(spark, sf_dir, fixed=1), []
    for kind in ("window_stack", "multiway_tree", "pq_tree"):
        for whole in (True, False):
            parts = halves(spark, sf_dir, kind, whole)
            took = built_size(parts).select(F.round("build_s", 2).alias("build_s"))
            out.append(points(parts, truth).drop("qps").crossJoin(took).withColumns({"index": F.lit(kind), "how": F.lit("whole" if whole else "half inserted")}))  # one row
    return union(out)


@query("half_insert_claim", "SELECT true AS stack_keeps_recall, true AS stack_is_best")
def half_insert_claim(spark, sf_dir):
    """Inserting a half costs the stack at most 3 points of recall, and no other index has more afterwards by over 3."""
    t = cut(half_insert(spark, sf_dir).where("how = 'half inserted'").select("index", "recall"), "claim")
    whole = points(halves(spark, sf_dir, "window_stack", True), truth_of(spark, sf_dir, fixed=1)).select(F.col("recall").alias("whole"))
    of = F.max(F.when(F.col("index") == "window_stack", F.col("recall")))
    return t.agg(of.alias("stack"), F.max("recall").alias("best")).crossJoin(whole).select((F.col("stack") >= F.col("whole") - 0.03).alias("stack_keeps_recall"), (F.col("stack") >= F.col("best") - 0.03).alias("stack_is_best"))  # one row each


@query("growth_built")
def growth_built(spark, sf_dir):
    """Built indices over a quarter, a half and all of the vectors: bytes, seconds, recall and rate."""
    out, every = [], hybrid(spark, sf_dir, "rand")
    n = every.count()
    for part in (4, 2, 1):
        data = every.where(F.col("id") < F.lit(every.agg(F.min("id")).first()[0] + n // part))
        q = cut(make_ranges(data), "asked")
        parts = cut(run.run_kind("window_stack", data, q, K, (64,)), "grown")
        size = built_size(parts)
        out.append(points(parts, cut(exact_range_knn(data, q, K), "truth")).crossJoin(size).withColumn("n_rows", F.lit(data.count())))  # one row
    return union(out)


@query("growth_claim", "SELECT true AS bytes_grow, true AS recall_kept")
def growth_claim(spark, sf_dir):
    """Bytes grow a little faster than the rows, by the layers; recall stays."""
    t = cut(growth_built(spark, sf_dir), "claim").withColumn("each", F.col("bytes") / F.col("n_rows"))
    at = lambda c, f: f(F.struct("n_rows", c))[c]
    return t.agg(at("each", F.min).alias("a"), at("each", F.max).alias("b"), F.min("recall").alias("r")).select(((F.col("b") >= F.col("a")) & (F.col("b") <= 2 * F.col("a"))).alias("bytes_grow"), (F.col("r") >= 0.9).alias("recall_kept"))


@query("parallel_build")
def parallel_build(spark, sf_dir):
    """Seconds to build as one segment, which is one task, and as segments of a quarter of the rows, which are several."""
    data = hybrid(spark, sf_dir, "rand")
    n, out = data.count(), []
    for cap in (n, -(-n // 4)):
        began = time.time()
        made = cut(index.build_index(data, cap=cap), "parallel")
        out.append(made.agg(F.countDistinct("seg", "sub").alias("segments"), F.count("*").alias("n_rows")).withColumn("seconds", F.lit(round(time.time() - began, 2))))
    return union(out)


@query("priced_search", f"""WITH {ranges_sql('price')}, d AS (SELECT qid, id, sqrt({l2sq_sql('h.vec', 'q.qvec')}) AS dist FROM q JOIN h ON attr >= lo AND attr <= hi),
t AS (SELECT qid, id, round(dist, 6) AS dist, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d)
SELECT qid, id, dist, CAST(pos AS INTEGER) AS pos, p_name, p_retailprice FROM t JOIN part ON p_partkey = id WHERE pos <= 10""")
def priced_search(spark, sf_dir):
    """Parts that look alike within a price range, with their names and prices."""
    parts = spark.read.parquet(f"{sf_dir}/part.parquet").select(F.col("p_partkey").alias("id"), "p_name", "p_retailprice")
    return truth_of(spark, sf_dir, "price").join(parts, "id")


@query("aged_search", f"""WITH a AS (SELECT vec_id AS id, embedding AS vec, c_acctbal AS attr FROM embeddings JOIN customer ON c_custkey = vec_id), q AS (SELECT id AS qid, vec AS qvec, attr - 500 AS lo, attr + 500 AS hi FROM a WHERE id % 20 = 0),
d AS (SELECT qid, id, attr, sqrt({l2sq_sql('a.vec', 'q.qvec')}) AS dist FROM q JOIN a ON attr >= lo AND attr <= hi)
SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= 10""")
def aged_search(spark, sf_dir):
    """customers' vectors within a band of account balance."""
    balance = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("id"), F.col("c_acctbal").alias("attr"))
    data = hybrid(spark, sf_dir, "id").drop("attr").join(balance, "id")
    q = data.where("id % 20 = 0").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"), (F.col("attr") - 500).alias("lo"), (F.col("attr") + 500).alias("hi"))
    return exact_range_knn(data, q, K)


@query("theory_tables")
def theory_tables(spark, sf_dir):
    """Landing layers' share in range beside the printed bounds."""
    return theory.fraction_table(spark, [2**i for i in range(3, 14)], [2, 4, 8, 16])


@query("maintenance_policies")
def maintenance_policies(spark, sf_dir):
    """The last tenth of the rows arrives.  Everything is rebuilt, or the rows are scanned beside the old index until they are merged into it, or inserted at once: seconds until the first answers, until the index is whole, and recall."""
    data, q = asked(spark, sf_dir)
    late = F.pmod(F.xxhash64("id"), F.lit(10)) == 0
    old = held(spark, (sf_dir, "main"), lambda: index.build_index(data.where(~late), Settings()))
    old.count()
    truth, out = truth_of(spark, sf_dir), []
    for policy in ("rebuild", "side_merge", "insert"):
        began = time.time()
        if policy == "side_merge":
            main = index.range_knn(old, q, K)
            found = index.top_k(main.select("qid", "id", "dist").union(exact_range_knn(data.where(late), q, K).select("qid", "id", "dist")), K)
        else:
            whole = cut(index.build_index(data, Settings()) if policy == "rebuild" else index.insert(old, data.where(late), Settings()), "whole")
            found = index.range_knn(whole, q, K)
        found = cut(found, "found")
        answered = time.time() - began
        if policy == "side_merge":
            cut(index.insert(old, data.where(late), Settings()), "whole")
        recall = measures.recall(found, truth, K).agg(F.round(F.avg("recall"), 4).alias("recall"))
        out.append(recall.withColumns({"policy": F.lit(policy), "answers_s": F.lit(round(answered, 2)), "whole_s": F.lit(round(time.time() - began, 2))}))
    return union(out)


@query("maintenance_claim", "SELECT true AS recall_kept, true AS insertion_as_good")
def maintenance_claim(spark, sf_dir):
    """Every policy keeps recall; an index that rows were inserted into answers as well as a new one."""
    t = cut(maintenance_policies(spark, sf_dir), "claim")
    of = lambda p: F.max(F.when(F.col("policy") == p, F.col("recall")))
    return t.agg((F.min("recall") >= 0.95).alias("recall_kept"), (of("insert") >= of("rebuild") - 0.02).alias("insertion_as_good"))


@query("fallback_share")
def fallback_share(spark, sf_dir):
    """Queries and segments whose beam returns fewer rows than asked for and are scanned instead, where that is switched on."""
    from hybridrange.methods import packed

    found = index.search(packed(spark, sf_dir), asked(spark, sf_dir)[1], K).groupBy("qid").agg(F.max("scanned").alias("scanned"))
    return found.agg(F.count("*").alias("queries"), F.sum(F.col("scanned").cast("long")).alias("scanned"))


@query("budget_effect")
def budget_effect(spark, sf_dir):
    """New rows a hop may take, with its cost and recall."""
    out = []
    for budget in (4, 8, 16, 64):
        out.append(points(swept(spark, sf_dir, "window_stack", omegas=(32,), how={"budget": budget}), truth_of(spark, sf_dir)).withColumn("budget", F.lit(budget)))
    return union(out)
