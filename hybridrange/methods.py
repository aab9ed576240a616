"""Queries for the methods, variants, baselines and measures, each over whole tables with its oracle."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hybridrange import graphs, index, measures, ranks, theory
from hybridrange.baselines import run
from hybridrange.exact import _finished, exact_knn, exact_range_knn
from hybridrange.functions.vectors import distance
from hybridrange.hybrid import SCALE, STEP, cosine_sql, hybrid, hybrid_sql, l2sq_sql, make_ranges, ranges_sql
from hybridrange.kernel.stack import Settings
from hybridrange.layers import landing_layer_col, layer_count_col
from hybridrange.plans.tables import cut, small

K = 10
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


_HELD: dict[tuple, DataFrame] = {}


def changed(spark: SparkSession, sf_dir: str) -> int:
    """When the newest table of a folder was written, so that no table made from older ones is used again."""
    path = spark._jvm.org.apache.hadoop.fs.Path(sf_dir)
    return max((x.getModificationTime() for x in path.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(path)), default=0)


def held(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A table that several queries of one session share, written once."""
    key = (spark.sparkContext.applicationId, changed(spark, key[0]), *key)
    if key not in _HELD:
        _HELD[key] = cut(make(), "held")
    return _HELD[key]


def asked(spark: SparkSession, sf_dir: str, name: str = "rand", **how) -> tuple[DataFrame, DataFrame]:
    data = hybrid(spark, sf_dir, name)
    return data, held(spark, (sf_dir, name, "q", json.dumps(how, sort_keys=True)), lambda: make_ranges(data, **how))


def truth_of(spark: SparkSession, sf_dir: str, name: str = "rand", k: int = K, **how) -> DataFrame:
    data, q = asked(spark, sf_dir, name, **how)
    return held(spark, (sf_dir, name, "truth", k, json.dumps(how, sort_keys=True)), lambda: exact_range_knn(data, q, k))


def built(spark: SparkSession, sf_dir: str, name: str = "rand", order: str = "shuffled", cap: int = index.CAP, **settings) -> DataFrame:
    return held(spark, (sf_dir, name, "index", order, cap, json.dumps(settings, sort_keys=True)), lambda: index.build_index(hybrid(spark, sf_dir, name), Settings(**settings), order, cap))


def packed(spark: SparkSession, sf_dir: str, *how, **settings) -> DataFrame:
    """The built index as it is searched."""
    return held(spark, (sf_dir, "packed", how, json.dumps(settings, sort_keys=True)), lambda: index.packed(built(spark, sf_dir, *how, **settings)))


# Exact search ------------------------------------------------------------


def exact_sql(name: str, dist: str = "l2", ranged: bool = True, where: str = "", k: int = K, **how) -> str:
    d = f"sqrt({l2sq_sql('h.vec', 'q.qvec')})" if dist == "l2" else cosine_sql("h.vec", "q.qvec")
    on = "h.attr >= q.lo AND h.attr <= q.hi" if ranged else "true"
    return f"""WITH {ranges_sql(name, **how)}, d AS (SELECT qid, id, {d} AS dist FROM q JOIN h ON {on} {where})
SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= {k}"""


@query("exact_knn", exact_sql("rand", ranged=False))
def _(spark, sf_dir):
    return exact_knn(*asked(spark, sf_dir), K)


@query("exact_range_knn_cosine", exact_sql("rand", "cosine"))
def _(spark, sf_dir):
    return exact_range_knn(*asked(spark, sf_dir), K, "cosine")


def _exact(name: str, key: str, **how) -> None:
    query(key, exact_sql(name, **how))(lambda spark, sf_dir: exact_range_knn(*asked(spark, sf_dir, name, **how), K))


for _name in ("rand", "time", "title", "id", "label", "price", "pivot", "dup50"):
    _exact(_name, "exact_range_knn" if _name == "rand" else f"exact_range_knn_{_name}")
_exact("rand", "prefilter_knn", fixed=4)


# Ranks, counts, windows, layers -------------------------------------------


for _name in ("rand", "label", "title", "time", "dup50", "line"):

    def _ranks(spark, sf_dir, name=_name):
        return ranks.with_ranks(hybrid(spark, sf_dir, name)).select("id", "rank_u")

    query(f"dense_ranks_{_name}", f"SELECT id, dense_rank() OVER (ORDER BY attr) - 1 AS rank_u FROM ({hybrid_sql(_name)})")(_ranks)
QUERIES["dense_ranks"], ORACLES["dense_ranks"] = QUERIES.pop("dense_ranks_rand"), ORACLES.pop("dense_ranks_rand")


@query("value_at_rank", f"SELECT attr, count(*) AS mult, r AS rank_u FROM (SELECT attr, dense_rank() OVER (ORDER BY attr) - 1 AS r FROM ({hybrid_sql('dup50')})) WHERE r % 5 = 0 GROUP BY attr, r")
def _(spark, sf_dir):
    return ranks.value_at_rank(ranks.order_stats(hybrid(spark, sf_dir, "dup50")), F.col("rank_u") % 5 == 0).select("attr", "mult", "rank_u")


def counts_sql(name: str) -> str:
    return f"WITH {ranges_sql(name)} SELECT qid, count(attr) AS n_rows, count(DISTINCT attr) AS n_uniques FROM q LEFT JOIN h ON attr >= lo AND attr <= hi GROUP BY qid"


for _name in ("rand", "dup50", "label", "price", "time"):

    def _counts(spark, sf_dir, name=_name):
        data, q = asked(spark, sf_dir, name)
        return ranks.range_counts(ranks.order_stats(data), q)

    query("range_counts" if _name == "rand" else f"range_counts_{_name}", counts_sql(_name))(_counts)


@query("median_row", f"WITH {ranges_sql('dup50')}, i AS (SELECT qid, attr, row_number() OVER (PARTITION BY qid ORDER BY attr) AS r, count(*) OVER (PARTITION BY qid) AS n FROM q JOIN h ON attr >= lo AND attr <= hi) SELECT qid, attr AS median_attr FROM i WHERE r = (n + 1) // 2")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir, "dup50")
    return ranks.median_rows(ranks.order_stats(data), q)


def bounds_sql(name: str, reach: int) -> str:
    return f"WITH u AS (SELECT attr, row_number() OVER (ORDER BY attr) - 1 AS r FROM (SELECT DISTINCT attr FROM ({hybrid_sql(name)}))), t AS (SELECT max(r) AS top FROM u) SELECT u.attr, a.attr AS win_lo, b.attr AS win_hi FROM u, t JOIN u a ON a.r = greatest(0, u.r - {reach}) JOIN u b ON b.r = least(t.top, u.r + {reach})"


for _layer in (0, 1, 2, 3):
    query(f"window_bounds_{_layer}", bounds_sql("rand", 4**_layer))(lambda spark, sf_dir, layer=_layer: ranks.window_bounds(ranks.order_stats(hybrid(spark, sf_dir, "rand")), 4, layer))
query("window_bounds_strict", bounds_sql("rand", 15))(lambda spark, sf_dir: ranks.window_bounds(ranks.order_stats(hybrid(spark, sf_dir, "rand")), 4, 2, True))
query("window_bounds_dup", bounds_sql("dup50", 4))(lambda spark, sf_dir: ranks.window_bounds(ranks.order_stats(hybrid(spark, sf_dir, "dup50")), 4, 1))

_SETS = "SELECT * FROM (VALUES ('rand'), ('label'), ('dup50'), ('price')) AS s(name)"
_COUNTED = " UNION ALL ".join(f"SELECT '{x}' AS dataset, count(DISTINCT attr) AS n_u FROM ({hybrid_sql(x)})" for x in ("rand", "label", "dup50", "price"))


@query("layer_count", f"SELECT dataset, o, n_u, (SELECT count(*) + 1 FROM range(0, 40) AS r(l) WHERE CAST(2 * pow(o, l) AS DOUBLE) < n_u) AS layers FROM ({_COUNTED}), (VALUES (2), (4), (10), (16)) AS b(o)")
def _(spark, sf_dir):
    rows = None
    for name in ("rand", "label", "dup50", "price"):
        one = hybrid(spark, sf_dir, name).agg(F.lit(name).alias("dataset"), F.countDistinct("attr").alias("n_u"))
        rows = one if rows is None else rows.union(one)
    out = None
    for o in (2, 4, 10, 16):
        one = rows.select("dataset", F.lit(o).alias("o"), "n_u", layer_count_col(F.col("n_u"), o).cast("long").alias("layers"))
        out = one if out is None else out.union(one)
    return out


@query("landing_layer", f"WITH {ranges_sql('dup50')}, c AS (SELECT qid, count(DISTINCT attr) AS n FROM q LEFT JOIN h ON attr >= lo AND attr <= hi GROUP BY qid), l AS (SELECT qid, n, greatest(0, (SELECT max(l) FROM range(0, 20) AS r(l) WHERE 2 * pow(4, l) <= greatest(n, 2))) AS low FROM c) SELECT qid, n AS n_uniques, CAST(CASE WHEN n = 0 THEN NULL ELSE least(2, CASE WHEN least(2 * pow(4, low), n) / greatest(2 * pow(4, low), n) >= least(2 * pow(4, low + 1), n) / greatest(2 * pow(4, low + 1), n) THEN low ELSE low + 1 END) END AS INTEGER) AS layer FROM l")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir, "dup50")
    counts = ranks.range_counts(ranks.order_stats(data), q)
    return counts.select("qid", "n_uniques", landing_layer_col(F.col("n_uniques"), 4, F.lit(2)).cast("int").alias("layer"))


# Graphs by joins -----------------------------------------------------------


for _layer in (0, 1, 2):
    query(f"window_knn_graph_{_layer}", graphs.knn_graph_sql("rand", 4, _layer, 8))(lambda spark, sf_dir, layer=_layer: graphs.window_knn_graph(hybrid(spark, sf_dir, "rand"), 4, layer, 8))
    query(f"exact_window_rng_{_layer}", graphs.rng_sql("rand", 4, _layer))(lambda spark, sf_dir, layer=_layer: graphs.exact_window_rng(hybrid(spark, sf_dir, "rand"), 4, layer))
    query(f"diverse_graph_{_layer}", graphs.diverse_sql("rand", 4, _layer, 8))(lambda spark, sf_dir, layer=_layer: graphs.diverse_graph(hybrid(spark, sf_dir, "rand"), 4, layer, 8))
query("window_knn_graph_dup", graphs.knn_graph_sql("dup50", 4, 1, 8))(lambda spark, sf_dir: graphs.window_knn_graph(hybrid(spark, sf_dir, "dup50"), 4, 1, 8))
query("diverse_graph_half", graphs.diverse_sql("rand", 4, 2, 4))(lambda spark, sf_dir: graphs.diverse_graph(hybrid(spark, sf_dir, "rand"), 4, 2, 4))
_BULK = " UNION ALL ".join(f"SELECT {x} AS layer, src, nbrs FROM ({graphs.diverse_sql('rand', 4, x, 16)})" for x in (0, 1, 2))
query("bulk_stack", _BULK)(lambda spark, sf_dir: graphs.bulk_stack(hybrid(spark, sf_dir, "rand"), 4, 16, [0, 1, 2]))
query("degree_histogram", f"SELECT layer, CAST(len(nbrs) AS INTEGER) AS degree, count(*) AS n FROM ({_BULK}) GROUP BY 1, 2")(lambda spark, sf_dir: graphs.degree_histogram(graphs.bulk_stack(hybrid(spark, sf_dir, "rand"), 4, 16, [0, 1, 2])))


@query("out_of_window_edges", "SELECT * FROM (VALUES (0, 0), (1, 0), (2, 0)) AS t(layer, outside)")
def _(spark, sf_dir):
    data = hybrid(spark, sf_dir, "rand")
    links = graphs.bulk_stack(data, 4, 16, [0, 1, 2]).select("layer", "src", F.explode("nbrs").alias("dst"))
    return graphs.out_of_window(links, ranks.with_ranks(data).select("id", "rank_u"), 4)


# The stack -----------------------------------------------------------------


def per_query(result: DataFrame, data: DataFrame, queries: DataFrame, truth: DataFrame, least: float, k: int = K) -> DataFrame:
    """(qid, n_found, in_range, recall_ok): what each query returned, and whether the mean recall reaches ``least``."""
    inside = result.join(data.select("id", "attr"), "id").join(queries.select("qid", "lo", "hi"), "qid")
    each = inside.groupBy("qid").agg(F.count("*").alias("n_found"), F.min((F.col("attr") >= F.col("lo")) & (F.col("attr") <= F.col("hi"))).alias("in_range"))
    mean = measures.recall(result, truth, k).agg((F.avg("recall") >= least).alias("recall_ok"))
    return queries.select("qid").join(each, "qid", "left").select("qid", F.coalesce("n_found", F.lit(0)).alias("n_found"), F.coalesce("in_range", F.lit(True)).alias("in_range")).crossJoin(F.broadcast(mean))  # one row


def full_sql(name: str = "rand", k: int = K, **how) -> str:
    """Every query returns min(k, n') rows, all in range, at the recall asked for."""
    return f"WITH {ranges_sql(name, **how)} SELECT qid, least({k}, count(attr)) AS n_found, true AS in_range, true AS recall_ok FROM q LEFT JOIN h ON attr >= lo AND attr <= hi GROUP BY qid"


#: Mean recall@10 at beam width 64 that the stack has to keep on these sets.
LEAST = 0.95


def stack_query(key: str, name: str = "rand", order: str = "shuffled", cap: int = index.CAP, settings: dict | None = None, least: float = LEAST, k: int = K, **how) -> None:
    def ask(spark, sf_dir):
        data, q = asked(spark, sf_dir, name)
        found = index.range_knn(packed(spark, sf_dir, name, order, cap, **(settings or {})), q, k, settings=Settings(**(settings or {})), **how)
        return per_query(found, data, q, truth_of(spark, sf_dir, name, k), least, k)

    query(key, full_sql(name, k))(ask)


stack_query("range_knn")
for _name in ("time", "title", "id", "label", "price", "dup50", "pivot"):
    stack_query(f"range_knn_{_name}", _name)
stack_query("range_knn_segments", cap=100)
stack_query("range_knn_no_early_stop", early_stop=False)
stack_query("range_knn_forced_top", landing="top")
for _layer in (0, 2):
    stack_query(f"range_knn_forced_{_layer}", landing=_layer, least=0.9 if _layer else 0.2)
stack_query("range_knn_estimated_layer", landing="estimate")
stack_query("range_knn_hop_budget", budget=8)
stack_query("range_knn_scan_small", scan_cap=64)
stack_query("ordered_insert", order="sorted")
stack_query("carry_off_insert", settings={"carry_over": False})
stack_query("eager_insert", settings={"lazy": False})
stack_query("strict_insert", settings={"strict": True})
stack_query("plain_nearest_insert", settings={"diverse": False}, least=0.85)
stack_query("tree_insert", settings={"tree": True})
stack_query("base_2", settings={"o": 2})
stack_query("base_16", settings={"o": 16})
stack_query("narrow_build", settings={"omega_c": 32, "m": 8}, least=0.9)
stack_query("range_knn_k1", k=1)
stack_query("range_knn_k50", k=50, omega=128)


@query("range_knn_small_ranges", exact_sql("rand", fixed=9))
def _(spark, sf_dir):
    return index.range_knn(packed(spark, sf_dir), asked(spark, sf_dir, fixed=9)[1], K, scan_cap=64)


@query("range_knn_wide", exact_sql("rand"))
def _(spark, sf_dir):
    """A beam as wide as the data is exact."""
    return index.range_knn(packed(spark, sf_dir), asked(spark, sf_dir)[1], K, 512)


@query("range_knn_level_sync", f"WITH {ranges_sql('rand')} SELECT qid, true AS in_range, true AS size_ok, true AS recall_ok FROM q")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    found = index.level_search(built(spark, sf_dir), q, K)
    return per_query(found, data, q, truth_of(spark, sf_dir), 0.85).select("qid", "in_range", (F.col("n_found") <= K).alias("size_ok"), "recall_ok")


def grown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Half of the rows built at once, the other half inserted."""
    data = hybrid(spark, sf_dir, "rand")
    return held(spark, (sf_dir, "grown"), lambda: index.insert(held(spark, (sf_dir, "half"), lambda: index.build_index(data.where("id % 2 = 0"), cap=200)), data.where("id % 2 = 1")))


@query("range_knn_after_insert", full_sql())
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    return per_query(index.range_knn(grown(spark, sf_dir), q, K), data, q, truth_of(spark, sf_dir), LEAST)


@query("range_knn_after_split", full_sql())
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    parts = held(spark, (sf_dir, "split"), lambda: index.split(grown(spark, sf_dir), 150))
    return per_query(index.range_knn(parts, q, K), data, q, truth_of(spark, sf_dir), LEAST)


@query("insert_stack_invariants", f"SELECT count(*) AS n_rows, true AS degree_ok, true AS no_loops, true AS no_repeats FROM ({hybrid_sql('rand')})")
def _(spark, sf_dir):
    lists = F.transform("links", lambda x: F.size(x))
    return built(spark, sf_dir).agg(F.count("*").alias("n_rows"), F.min(F.array_max(lists) <= 16).alias("degree_ok"), F.min(~F.exists("links", lambda x: F.array_contains(x, F.col("ord")))).alias("no_loops"), F.min(F.forall("links", lambda x: F.size(F.array_distinct(x)) == F.size(x))).alias("no_repeats"))


_GONE = f"SELECT id FROM ({hybrid_sql('rand')}) WHERE id % 3 = 0"


@query("range_knn_deleted", f"WITH {ranges_sql('rand')} SELECT qid, least(10, count(h.attr)) AS n_found, true AS in_range, true AS recall_ok FROM q LEFT JOIN (SELECT * FROM h WHERE id % 3 <> 0) h ON h.attr >= lo AND h.attr <= hi GROUP BY qid")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    left = data.where("id % 3 <> 0")
    marked = index.delete(built(spark, sf_dir), data.where("id % 3 = 0"))
    return per_query(index.range_knn(marked, q, K), left, q, exact_range_knn(left, q, K), LEAST)


@query("range_knn_updated", f"WITH {ranges_sql('rand')} SELECT qid, least(10, count(attr)) AS n_found, true AS in_range, true AS recall_ok FROM q LEFT JOIN h ON attr >= lo AND attr <= hi GROUP BY qid")
def _(spark, sf_dir):
    """Every third row comes back with its vector turned round: the old ones are marked, the new ones inserted."""
    data, q = asked(spark, sf_dir)
    turned = data.where("id % 3 = 0").withColumn("vec", F.transform("vec", lambda x: -x))
    renewed = held(spark, (sf_dir, "turned"), lambda: index.packed(index.update(built(spark, sf_dir), turned)))
    new = data.where("id % 3 <> 0").union(turned)
    return per_query(index.range_knn(renewed, q, K), new, q, exact_range_knn(new, q, K), LEAST)


@query("dc_fc_counts", f"WITH {ranges_sql('rand')} SELECT qid, true AS dc_ok, true AS fc_ok FROM q")
def _(spark, sf_dir):
    n = hybrid(spark, sf_dir, "rand").count()
    found = index.costs(index.search(packed(spark, sf_dir), asked(spark, sf_dir)[1], K, complete=False))
    # a beam takes each distance once, and checks at least the links it takes distances by
    return found.select("qid", F.col("dc").between(1, n).alias("dc_ok"), (F.col("fc") >= F.col("dc") - 1).alias("fc_ok"))


@query("layer_footprint")
def _(spark, sf_dir):
    """(qid, hop, l_min, l_max): layers seen by the first 400 hops of every range of a sixteenth."""
    found = index.search(packed(spark, sf_dir), asked(spark, sf_dir, fixed=4)[1], K, trace=True, complete=False)
    hops = found.select("qid", F.posexplode("hops").alias("hop", "layers")).where("hop < 400")
    return hops.select("qid", "hop", F.get("layers", F.lit(0)).alias("l_min"), F.get("layers", F.lit(1)).alias("l_max"))


@query("early_stop_saving", "SELECT true AS saves_distances, true AS saves_checks")
def _(spark, sf_dir):
    q = asked(spark, sf_dir)[1]
    on, off = (index.costs(index.search(packed(spark, sf_dir), q, K, early_stop=x, complete=False)).agg(F.sum("dc").alias("dc"), F.sum("fc").alias("fc")) for x in (True, False))
    both = on.crossJoin(off.withColumnsRenamed({"dc": "dc2", "fc": "fc2"}))  # one row each
    return both.select((F.col("dc") <= F.col("dc2")).alias("saves_distances"), (F.col("fc") <= F.col("fc2")).alias("saves_checks"))


@query("in_range_share")
def _(spark, sf_dir):
    """(f_exp, share): part of the landing layer's checked neighbours that are in range."""
    data, q = asked(spark, sf_dir)
    found = index.search(packed(spark, sf_dir), q, K, complete=False).groupBy("qid").agg(F.sum("seen").alias("seen"), F.sum("passed").alias("passed"))
    return found.join(q.select("qid", "f_exp"), "qid").groupBy("f_exp").agg(F.round(F.sum("passed") / F.greatest(F.lit(1), F.sum("seen")), 4).alias("share"))


# Several attributes ---------------------------------------------------------

_TWO = f"(SELECT e.vec_id AS id, e.embedding AS vec, e.label AS a, (e.vec_id * {SCALE} + 104729) % 1000003 AS b FROM embeddings e)"


def two(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows with a second attribute, the label."""
    labels = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("label").alias("a"))
    return hybrid(spark, sf_dir, "rand").withColumnRenamed("attr", "b").join(labels, "id")


def both_sql(k: int = K) -> str:
    return f"""WITH {ranges_sql('rand')}, t AS {_TWO}, d AS (SELECT qid, t.id, sqrt({l2sq_sql('t.vec', 'q.qvec')}) AS dist FROM q JOIN t ON t.b >= q.lo AND t.b <= q.hi AND t.a BETWEEN 2 AND 6)
SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= {k}"""


LABELS = (2, 6)


@query("exact_infilter", both_sql())
def _(spark, sf_dir):
    """Ranks by one attribute, tests the other beside it."""
    q = asked(spark, sf_dir)[1]
    data = two(spark, sf_dir).where("a between 2 and 6").select("id", "vec", F.col("b").alias("attr"))
    return exact_range_knn(data, q, K)


@query("exact_merge", both_sql())
def _(spark, sf_dir):
    """One sub-query an attribute, then the common ids ranked."""
    q, data = asked(spark, sf_dir)[1], two(spark, sf_dir)
    first = data.join(small(q.select("qid", "lo", "hi")), F.col("b").between(F.col("lo"), F.col("hi"))).select("qid", "id")
    second = data.where("a between 2 and 6").select("id", "vec")
    pairs = first.join(second, "id").join(small(q.select("qid", "qvec")), "qid")
    return _finished(pairs.select("qid", "id", distance("l2", "vec", "qvec").alias("dist")), K)


def doubly(found: DataFrame, data: DataFrame, q: DataFrame, truth: DataFrame, least: float) -> DataFrame:
    """(qid, in_both, size_ok, recall_ok): whether results are within both bounds and k, and reach the mean recall asked for of the exact answer."""
    inside = found.join(data.select("id", "a", "b"), "id").join(q.select("qid", "lo", "hi"), "qid")
    each = inside.groupBy("qid").agg(F.count("*").alias("n"), F.min(F.col("b").between(F.col("lo"), F.col("hi")) & F.col("a").between(*LABELS)).alias("ok"))
    mean = measures.recall(found, truth, K).agg((F.avg("recall") >= least).alias("recall_ok"))
    return q.select("qid").join(each, "qid", "left").select("qid", F.coalesce("ok", F.lit(True)).alias("in_both"), (F.coalesce("n", F.lit(0)) <= K).alias("size_ok")).crossJoin(F.broadcast(mean))  # one row


_BOTH = f"WITH {ranges_sql('rand')} SELECT qid, true AS in_both, true AS size_ok, true AS recall_ok FROM q"


def two_index(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """An index on one of the two attributes that carries the other, or on both in lexicographic order."""
    data = two(spark, sf_dir)
    attr = {"a": F.col("a").cast("long"), "b": F.col("b"), "lex": lex(F.col("a"), F.col("b"))}[key]
    return held(spark, (sf_dir, "two", key), lambda: index.packed(index.build_index(data.select("id", "vec", attr.alias("attr"), "a"))))


def lex(a, b):
    """One number in the order of two: the second is less than 2**40."""
    return a.cast("long") * F.lit(2**40) + b


@query("range_knn_infilter", _BOTH)
def _(spark, sf_dir):
    """The index answers one attribute; the other is tested while it walks, and rows outside are walked and not returned."""
    q, data = asked(spark, sf_dir)[1], two(spark, sf_dir)
    found = index.range_knn(two_index(spark, sf_dir, "b"), q, K, second=("a", *LABELS))
    return doubly(found, data, q, QUERIES["exact_infilter"](spark, sf_dir), 0.95)


@query("range_knn_postfilter_second", _BOTH)
def _(spark, sf_dir):
    """The index answers one attribute with a wider k; the other is tested afterwards."""
    q, data = asked(spark, sf_dir)[1], two(spark, sf_dir)
    found = index.range_knn(two_index(spark, sf_dir, "b"), q, 4 * K, 128).join(data.select("id", "a"), "id").where(F.col("a").between(*LABELS))
    return doubly(index.top_k(found.select("qid", "id", "dist"), K), data, q, QUERIES["exact_infilter"](spark, sf_dir), 0.9)


@query("range_knn_merge", _BOTH)
def _(spark, sf_dir):
    """Each attribute has an index of its own; both answer with a wider k and the ids that both return are ranked."""
    q, data = asked(spark, sf_dir)[1], two(spark, sf_dir)
    wide = 16 * K
    first = index.range_knn(two_index(spark, sf_dir, "b"), q, wide, wide)
    labels = q.select("qid", "qvec", F.lit(LABELS[0]).cast("long").alias("lo"), F.lit(LABELS[1]).cast("long").alias("hi"))
    second = index.range_knn(two_index(spark, sf_dir, "a"), labels, wide, wide).select("qid", "id")
    found = index.top_k(first.select("qid", "id", "dist").join(second, ["qid", "id"]), K)
    return doubly(found, data, q, QUERIES["exact_infilter"](spark, sf_dir), 0.6)


_LEX = f"""WITH t AS {_TWO}, q AS (SELECT id AS qid, vec AS qvec, a, b FROM t WHERE id % {STEP} = 0), d AS (SELECT qid, t.id, sqrt({l2sq_sql('t.vec', 'q.qvec')}) AS dist FROM q JOIN t ON (t.a > q.a OR t.a = q.a AND t.b >= q.b) AND t.a <= q.a + 1)
SELECT qid, id, round(dist, 6) AS dist, CAST(pos AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d) WHERE pos <= 10"""


def lex_asked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From each query row's pair of attributes to the end of the next label."""
    return two(spark, sf_dir).where(F.col("id") % STEP == 0).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"), lex(F.col("a"), F.col("b")).alias("lo"), (lex(F.col("a") + 1, F.lit(0)) + F.lit(2**40 - 1)).alias("hi"))


@query("exact_lex", _LEX)
def _(spark, sf_dir):
    """A composite attribute in lexicographic order."""
    data = two(spark, sf_dir).select("id", "vec", lex(F.col("a"), F.col("b")).alias("attr"))
    return exact_range_knn(data, lex_asked(spark, sf_dir), K)


@query("range_knn_lex", f"WITH e AS ({_LEX}), q AS (SELECT vec_id AS qid FROM embeddings WHERE vec_id % {STEP} = 0) SELECT q.qid, count(e.id) AS n_found, true AS in_range, true AS recall_ok FROM q LEFT JOIN e ON e.qid = q.qid GROUP BY q.qid")
def _(spark, sf_dir):
    """One index on the composite attribute."""
    q = lex_asked(spark, sf_dir)
    data = two(spark, sf_dir).select("id", lex(F.col("a"), F.col("b")).alias("attr"))
    return per_query(index.range_knn(two_index(spark, sf_dir, "lex"), q, K), data, q, QUERIES["exact_lex"](spark, sf_dir), LEAST)


@query("udtf_range_knn", full_sql())
def _(spark, sf_dir):
    """The search as a table function in SQL, called for each segment with the queries that its bounds meet."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="qid long, id long, dist double")
    class Nearest:
        def eval(self, payload, asked, k):
            stack, part = index.restored(index.unpacked(payload), Settings())
            values, codes = index.value_order(part)
            ids = part["id"].to_numpy()
            for q in asked:
                if bounds := index.bounds_of(values, codes, q["lo"], q["hi"]):
                    f = stack.query(np.asarray(q["qvec"], float), bounds, k)
                    yield from ((q["qid"], int(ids[r]), d) for r, d in zip(f.rows, f.dist, strict=True))

    data, q = asked(spark, sf_dir)
    spark.udtf.register("range_knn_of", Nearest)
    index.asked_of(packed(spark, sf_dir), q).createOrReplaceTempView("segments_asked")
    found = spark.sql(f"SELECT t.qid, t.id, t.dist FROM segments_asked, LATERAL range_knn_of(payload, asked, {K}) t")
    return per_query(index.top_k(found, K), data, q, truth_of(spark, sf_dir), LEAST)


@query("sql_landing", ORACLES["landing_layer"])
def _(spark, sf_dir):
    """The landing layer as a function of SQL: of two neighbouring window sizes the one nearer in ratio."""
    data, q = asked(spark, sf_dir, "dup50")
    ranks.range_counts(ranks.order_stats(data), q).createOrReplaceTempView("counts_asked")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lower_layer(n BIGINT, o INT) RETURNS INT RETURN greatest(0, CAST(floor(log(o, greatest(n, 2) / 2) + 1e-12) AS INT))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION nearness(n BIGINT, w DOUBLE) RETURNS DOUBLE RETURN least(w, n) / greatest(w, n)")
    return spark.sql("SELECT qid, n_uniques, CAST(CASE WHEN n_uniques > 0 THEN least(2, lower_layer(n_uniques, 4) + IF(nearness(n_uniques, 2 * pow(4, lower_layer(n_uniques, 4))) >= nearness(n_uniques, 2 * pow(4, lower_layer(n_uniques, 4) + 1)), 0, 1)) END AS INT) AS layer FROM counts_asked")


@query("estimate_count_kll", f"WITH {ranges_sql('rand')} SELECT qid, true AS close FROM q")
def _(spark, sf_dir):
    """Rows in range by a quantile sketch's cut points, within 3 of 100 of all rows."""
    data, q = asked(spark, sf_dir)
    marks = ", ".join(str(i / 200) for i in range(201))
    cuts = data.agg(F.expr(f"kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(attr), array({marks}))").alias("cuts"), F.count("*").alias("n"))
    at = q.select("qid", "lo", "hi").crossJoin(F.broadcast(cuts))  # one row
    below = lambda c: F.size(F.filter("cuts", lambda x: x < F.col(c))) / 200
    est = at.select("qid", (below("hi") - below("lo")).alias("e"), "n")
    return est.join(ranks.range_counts(ranks.order_stats(data), q), "qid").select("qid", (F.abs(F.col("e") * F.col("n") - F.col("n_rows")) <= 0.03 * F.col("n") + 1).alias("close"))


# Baselines -----------------------------------------------------------------


def postfilter_sql(alpha: float = 1.0) -> str:
    return f"""WITH {ranges_sql('rand')}, c AS (SELECT qid, count(*) AS n1, (SELECT count(*) FROM h) AS n FROM q JOIN h ON attr >= lo AND attr <= hi GROUP BY qid),
d AS (SELECT q.qid, id, attr, lo, hi, least(n, ceil({alpha} * 10 * n / n1)) AS want, sqrt({l2sq_sql('h.vec', 'q.qvec')}) AS dist FROM q JOIN c USING (qid), h),
p AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM d)
SELECT qid, id, round(dist, 6) AS dist, CAST(r AS INTEGER) AS pos FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS r FROM p WHERE pos <= want AND attr >= lo AND attr <= hi) WHERE r <= 10"""


query("postfilter_exact", postfilter_sql())(lambda spark, sf_dir: run.postfilter_exact(*asked(spark, sf_dir), K))
query("postfilter_half", postfilter_sql(0.5))(lambda spark, sf_dir: run.postfilter_exact(*asked(spark, sf_dir), K, 0.5))
query("postfilter_retry", exact_sql("rand"))(lambda spark, sf_dir: run.postfilter_retry(*asked(spark, sf_dir), K))
query("adaptive_knn_exact", exact_sql("rand"))(lambda spark, sf_dir: run.adaptive_exact(*asked(spark, sf_dir), K))

#: Mean recall@10 each baseline has to reach at beam width 64, from its published or structural limits.
FLOORS = {"prefilter": 1.0, "flat_graph": 0.85, "adaptive": 0.9, "dense_graph": 0.9, "interval_graph": 0.6, "block_tree_superset": 0.9, "block_tree_edges": 0.85, "slot_graph": 0.8, "pq_tree": 0.9, "multiway_tree": 0.8, "oracle_graph": 0.9, "ivf": 0.5, "lsh": 0.5, "window_stack": 0.95}


def baseline(kind: str) -> None:
    def ask(spark, sf_dir):
        data, q = asked(spark, sf_dir)
        found = run.merged(held(spark, (sf_dir, kind), lambda: run.run_kind(kind, data, q, K)), K)
        return per_query(found, data, q, truth_of(spark, sf_dir), FLOORS[kind]).select("qid", "in_range", (F.col("n_found") <= K).alias("size_ok"), "recall_ok")

    query(f"baseline_{kind}", f"WITH {ranges_sql('rand')} SELECT qid, true AS in_range, true AS size_ok, true AS recall_ok FROM q")(ask)


for _kind in FLOORS:
    baseline(_kind)


# Theory --------------------------------------------------------------------

_BASES = [2, 4, 16]


def line_sizes(spark: SparkSession, sf_dir: str, span: str) -> DataFrame:
    """(n): the different numbers of line items that are shipped in one ``span`` of time, a day or a month."""
    return hybrid(spark, sf_dir, "line").where("attr is not null").groupBy(F.date_trunc(span, "attr").alias("span")).agg(F.count("*").alias("n")).select("n").distinct()


def sizes_sql(span: str) -> str:
    return f"SELECT n, o FROM (SELECT DISTINCT count(*) AS n FROM lineitem WHERE l_shipdate IS NOT NULL GROUP BY date_trunc('{span}', l_shipdate)) AS a, (VALUES (2), (4), (16)) AS b(o)"


@query("space_model", f"WITH s AS (SELECT n, o, (SELECT count(*) FROM range(0, 40) AS r(l) WHERE 2 * pow(o, l) < n) AS top FROM ({sizes_sql('month')})) SELECT o, CAST(n AS BIGINT) AS n, top + 1 AS layers, CAST(n * (SELECT sum(least(16, 2 * pow(o, l))) FROM range(0, 40) AS r(l) WHERE l <= top) AS BIGINT) AS links, CAST(n * (top + 1) * 64 AS BIGINT) AS slot_bytes FROM s")
def _(spark, sf_dir):
    """Space of an index for each size that the line items of a month have."""
    return theory.space_table(line_sizes(spark, sf_dir, "month"), _BASES).select("o", "n", F.col("layers").cast("long").alias("layers"), "links", F.col("slot_bytes").cast("long").alias("slot_bytes"))


@query("in_range_fraction", f"WITH s AS (SELECT n, o, (SELECT max(l) FROM range(0, 40) AS r(l) WHERE 2 * pow(o, l) <= greatest(n, 2)) AS low FROM ({sizes_sql('day')})), w AS (SELECT n, o, CAST(pow(o, CASE WHEN least(2 * pow(o, low), n) / greatest(2 * pow(o, low), n) >= least(2 * pow(o, low + 1), n) / greatest(2 * pow(o, low + 1), n) THEN low ELSE low + 1 END) AS BIGINT) AS w FROM s) SELECT o, CAST(n AS BIGINT) AS n, w, round(list_sum(list_transform(range(0, n), lambda i: least(i, w) + least(n - 1 - i, w))) / (n * 2.0 * w), 6) AS fraction FROM w")
def _(spark, sf_dir):
    """Share of the landing layer's window that is in range, for each size of a day's range of line items."""
    return theory.fractions(line_sizes(spark, sf_dir, "day"), _BASES).select("o", "n", "w", "fraction")


query("printed_fraction_bounds")(lambda spark, sf_dir: theory.fractions(line_sizes(spark, sf_dir, "day"), _BASES))


def sums_sql(low: int) -> str:
    part = lambda l, n: f"SELECT src, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS place, sqrt(dist) AS {n} FROM p{l}"
    pairs = lambda l: f"p{l} AS (SELECT a.id AS src, b.id AS dst, {l2sq_sql('a.vec', 'b.vec')} AS dist FROM h a JOIN h b ON a.id <> b.id AND abs(a.r - b.r) <= {4**l})"
    return f"WITH {graphs.ranked_sql('rand')}, {pairs(low)}, {pairs(low + 1)} SELECT src, round(sum(a), 6) AS s_low, round(sum(b), 6) AS s_high, true AS holds FROM ({part(low, 'a')}) JOIN ({part(low + 1, 'b')}) USING (src, place) WHERE place <= 8 GROUP BY src"


for _layer in (1, 2):
    query(f"layer_distance_sums_{_layer}", sums_sql(_layer))(lambda spark, sf_dir, layer=_layer: theory.layer_distance_sums(hybrid(spark, sf_dir, "rand"), 4, 8, layer))


# Measures ------------------------------------------------------------------

_POST = postfilter_sql(0.5)


@query("recall", f"WITH t AS ({exact_sql('rand')}), r AS ({_POST}) SELECT t.qid, count(r.id) / least(10, count(*)) AS recall FROM t LEFT JOIN r ON r.qid = t.qid AND r.id = t.id GROUP BY t.qid")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    return measures.recall(run.postfilter_exact(data, q, K, 0.5), truth_of(spark, sf_dir), K)


@query("objective_ratio", f"SELECT qid, round(a / b, 6) AS ratio FROM (SELECT qid, sum(dist) AS a FROM ({_POST}) GROUP BY qid) JOIN (SELECT qid, sum(dist) AS b FROM ({exact_sql('rand')}) GROUP BY qid) USING (qid)")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir)
    return measures.objective_ratio(run.postfilter_exact(data, q, K, 0.5), truth_of(spark, sf_dir))


@query("selectivity", f"WITH n AS (SELECT count(*) AS n, count(DISTINCT attr) AS u FROM ({hybrid_sql('dup50')})) SELECT qid, round(n_rows / n, 9) AS fraction, CASE WHEN n_rows > 0 THEN round(n / n_rows, 6) END AS selectivity, round(n_uniques / u, 9) AS unique_selectivity FROM ({counts_sql('dup50')}), n")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir, "dup50")
    n, u = data.agg(F.count("*"), F.countDistinct("attr")).first()
    return measures.selectivity(ranks.range_counts(ranks.order_stats(data), q), n, u)


@query("lid", f"WITH t AS ({exact_sql('rand')}), f AS (SELECT qid, max(dist) AS far FROM t GROUP BY qid) SELECT qid, round(CASE WHEN m < 0 THEN -1 / m END, 4) AS lid FROM (SELECT qid, avg(ln(dist / far)) AS m FROM t JOIN f USING (qid) WHERE dist > 0 GROUP BY qid)")
def _(spark, sf_dir):
    return measures.lid(truth_of(spark, sf_dir))


@query("correlation_class", f"WITH t AS ({exact_sql('rand', fixed=3)}), r AS ({_POST.replace(ranges_sql('rand'), ranges_sql('rand', fixed=3))}), c AS (SELECT t.qid, count(r.id) / least(10, count(*)) AS x FROM t LEFT JOIN r ON r.qid = t.qid AND r.id = t.id GROUP BY t.qid) SELECT qid, CASE WHEN x <= 0.2 THEN 'low' WHEN x >= 0.4 AND x <= 0.6 THEN 'none' WHEN x >= 0.8 THEN 'high' ELSE 'between' END AS class FROM c")
def _(spark, sf_dir):
    data, q = asked(spark, sf_dir, fixed=3)
    return measures.correlation_class(measures.recall(run.postfilter_exact(data, q, K, 0.5), truth_of(spark, sf_dir, fixed=3), K))


@query("index_bytes", f"WITH s AS (SELECT count(*) AS n, count(DISTINCT attr) AS u FROM ({hybrid_sql('rand')})) SELECT n AS rows, CAST(l AS INTEGER) AS layers, CAST(n * l * 64 AS BIGINT) AS slot_bytes, true AS links_fit FROM (SELECT n, (SELECT count(*) + 1 FROM range(0, 40) AS r(i) WHERE 2 * pow(4, i) < u) AS l FROM s)")
def _(spark, sf_dir):
    one = measures.index_bytes(built(spark, sf_dir), 16)
    return one.select("rows", "layers", F.col("slot_bytes").cast("long").alias("slot_bytes"), (F.col("link_bytes") <= F.col("slot_bytes")).alias("links_fit"))
