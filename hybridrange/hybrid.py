"""Hybrid datasets (id, vec, attr) built from the given tables, and their query workloads.

Every dataset has a twin in DuckDB SQL, from which the oracles are composed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hybridrange import ranks
from hybridrange.plans.tables import table

#: Rows of this step in id are the stated query set.
STEP = 20
EXPONENTS = 11
#: The permuted attribute: a full cycle modulo a prime above every id here.
SCALE, SHIFT, PRIME = 7919, 104729, 1000003

_DATASETS: dict[str, tuple[str, str]] = {
    "rand": (f"(vec_id * {SCALE} + {SHIFT}) % {PRIME}", "embeddings"),
    "id": ("vec_id", "embeddings"),
    "label": ("label", "embeddings"),
    "time": ("ts", "embeddings JOIN events ON vec_id = event_id"),
    "title": ("url", "embeddings JOIN pages ON vec_id = page_id"),
    "price": ("p_retailprice", "embeddings JOIN part ON vec_id = p_partkey"),
}
_SOURCES = {"time": ("events", "event_id"), "title": ("pages", "page_id"), "price": ("part", "p_partkey")}


def hybrid_sql(name: str) -> str:
    """DuckDB SQL of a dataset."""
    if name.startswith("dup"):
        return f"SELECT vec_id AS id, embedding AS vec, 1 + (vec_id * {SCALE}) % {int(name[3:])} AS attr FROM embeddings"
    if name == "line":
        return "SELECT l_orderkey * 8 + l_linenumber AS id, [l_quantity / 50, l_extendedprice / 100000, l_discount * 10, l_tax * 10] AS vec, l_shipdate AS attr FROM lineitem"
    if name == "pivot":
        return f"SELECT id, vec, row_number() OVER (ORDER BY d, id) - 1 AS attr FROM (SELECT e.vec_id AS id, e.embedding AS vec, {l2sq_sql('e.embedding', 'p.embedding')} AS d FROM embeddings e, (SELECT embedding FROM embeddings ORDER BY vec_id LIMIT 1) p)"
    attr, source = _DATASETS[name]
    return f"SELECT vec_id AS id, embedding AS vec, {attr} AS attr FROM {source}"


def hybrid(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Columns id long, vec array, attr of any ordered type."""
    if name == "line":
        return table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id"), F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / 100000, F.col("l_discount") * 10, F.col("l_tax") * 10).alias("vec"), F.col("l_shipdate").alias("attr"))
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")
    if name == "pivot":
        from hybridrange.functions.vectors import l2sq

        first = e.orderBy("id").limit(1).select(F.col("vec").alias("p"))
        near = e.join(F.broadcast(first), how="cross").select("id", "vec", F.struct(l2sq("vec", "p").alias("d"), "id").alias("key"))  # one row on the other side
        return ranks.with_ranks(near, "key").select("id", "vec", F.col("rank_u").alias("attr"))
    if name in ("rand", "id"):
        return e.select("id", "vec", ((F.col("id") * SCALE + SHIFT) % PRIME if name == "rand" else F.col("id")).alias("attr"))
    if name == "label":
        return e.select("id", "vec", F.col("label").alias("attr"))
    if name.startswith("dup"):
        return e.select("id", "vec", (1 + (F.col("id") * SCALE) % int(name[3:])).alias("attr"))
    source, key = _SOURCES[name]
    other = table(spark, sf_dir, source).select(F.col(key).alias("id"), F.col(_DATASETS[name][0]).alias("attr"))
    return e.join(other, "id").select("id", "vec", "attr")


def l2sq_sql(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}::DOUBLE[], {b}::DOUBLE[]), lambda t: (t[1] - t[2]) * (t[1] - t[2])))"


def cosine_sql(a: str, b: str) -> str:
    d = lambda x, y: f"list_sum(list_transform(list_zip({x}::DOUBLE[], {y}::DOUBLE[]), lambda t: t[1] * t[2]))"
    return f"(1 - {d(a, b)} / (sqrt({d(a, a)}) * sqrt({d(b, b)})))"


def make_ranges(data: DataFrame, exponents: int = EXPONENTS, fixed: int | None = None, step: int = STEP) -> DataFrame:
    """Queries (qid, qvec, f_exp, lo, hi): each row whose id is a multiple of ``step`` asks for a range of a 2**-f_exp share.

    Widths are floor(n * 2**-f_exp) rows, at least one; starts are spread by a
    fixed rule over all ranks that leave room.
    """
    placed = ranks.with_positions(data.select("id", "attr"), "attr")
    n = placed.count()
    q = data.where(F.col("id") % step == 0).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    q = q.withColumn("f_exp", F.lit(fixed).cast("int") if fixed is not None else (F.floor(F.col("qid") / step) % exponents).cast("int"))
    q = q.withColumn("w", F.greatest(F.lit(1), F.floor(F.lit(n) / F.pow(F.lit(2.0), F.col("f_exp")))).cast("long"))
    q = q.withColumn("start", (F.col("qid") * SCALE + 13) % (F.lit(n) - F.col("w") + 1))
    at = placed.select("pos", "attr")
    low = q.join(at.withColumnsRenamed({"pos": "start", "attr": "lo"}), "start")
    return low.withColumn("end", F.col("start") + F.col("w") - 1).join(at.withColumnsRenamed({"pos": "end", "attr": "hi"}), "end").select("qid", "qvec", "f_exp", "lo", "hi")


def ranges_sql(name: str, exponents: int = EXPONENTS, fixed: int | None = None, step: int = STEP) -> str:
    """DuckDB common table expressions ``h`` (the data) and ``q`` (the queries)."""
    f = str(fixed) if fixed is not None else f"(id // {step}) % {exponents}"
    return f"""h AS ({hybrid_sql(name)}),
placed AS (SELECT attr, row_number() OVER (ORDER BY attr, id) - 1 AS pos FROM h),
q0 AS (SELECT id AS qid, vec AS qvec, CAST({f} AS INTEGER) AS f_exp, (SELECT count(*) FROM h) AS n FROM h WHERE id % {step} = 0),
q1 AS (SELECT *, CAST(greatest(1, floor(n / pow(2.0, f_exp))) AS BIGINT) AS w FROM q0),
q2 AS (SELECT *, (qid * {SCALE} + 13) % (n - w + 1) AS start FROM q1),
q AS (SELECT qid, qvec, f_exp, a.attr AS lo, b.attr AS hi FROM q2 JOIN placed a ON a.pos = start JOIN placed b ON b.pos = start + w - 1)"""
