"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, recall): share of the true rows found; with fewer than k in range, of those.  Queries without true rows are left out."""
    hits = truth.select("qid", "id").join(result.select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left")
    return hits.groupBy("qid").agg((F.count("hit") / F.least(F.lit(k), F.count("*"))).alias("recall"))


def objective_ratio(result: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, ratio): sum of the distances found over the least possible."""
    a, b = result.groupBy("qid").agg(F.sum("dist").alias("a")), truth.groupBy("qid").agg(F.sum("dist").alias("b"))
    return a.join(b, "qid").select("qid", F.round(F.try_divide("a", "b"), 6).alias("ratio"))


def selectivity(counts: DataFrame, n: int, n_u: int) -> DataFrame:
    """(qid, fraction, selectivity, unique_selectivity) of (qid, n_rows, n_uniques); null selectivity for empty ranges."""
    f = F.col("n_rows") / n
    return counts.select("qid", F.round(f, 9).alias("fraction"), F.round(F.try_divide(F.lit(1.0), f), 6).alias("selectivity"), F.round(F.col("n_uniques") / n_u, 9).alias("unique_selectivity"))


def lid(truth: DataFrame) -> DataFrame:
    """(qid, lid): minus one over the mean log ratio of each distance to the farthest; null where that is undefined."""
    far = truth.groupBy("qid").agg(F.max("dist").alias("far"))
    logs = truth.where("dist > 0").join(far, "qid").groupBy("qid").agg(F.avg(F.log(F.col("dist") / F.col("far"))).alias("m"))
    return logs.select("qid", F.round(F.when(F.col("m") < 0, -1 / F.col("m")), 4).alias("lid"))


def correlation_class(recalls: DataFrame) -> DataFrame:
    """(qid, class) by the recall of post-filtering."""
    r = F.col("recall")
    return recalls.select("qid", F.when(r <= 0.2, "low").when((r >= 0.4) & (r <= 0.6), "none").when(r >= 0.8, "high").otherwise("between").alias("class"))


def index_bytes(index: DataFrame, m: int) -> DataFrame:
    """(rows, layers, slot_bytes, link_bytes): size by fixed slots and by the links held, raw vectors and attributes left out."""
    one = index.agg(F.count("*").alias("rows"), F.max(F.size("links")).alias("layers"), F.sum(F.size("links") * (4 * m)).alias("slot_bytes"), F.sum(4 * F.aggregate("links", F.lit(0), lambda s, x: s + F.size(x))).cast("long").alias("link_bytes"))
    return one


def at_recall(points: DataFrame, level: float, value: str) -> DataFrame:
    """The cost at a recall level, by linear interpolation between the two points of the sweep (omega, recall, value) around it."""
    under = points.where(F.col("recall") <= level).agg(F.max_by(F.struct("recall", value), "recall").alias("u"))
    over = points.where(F.col("recall") >= level).agg(F.min_by(F.struct("recall", value), "recall").alias("v"))
    both = under.crossJoin(over)  # one row on either side
    share = F.when(F.col("v.recall") > F.col("u.recall"), (level - F.col("u.recall")) / (F.col("v.recall") - F.col("u.recall"))).otherwise(0.0)
    return both.select(F.lit(level).alias("level"), F.coalesce(F.col(f"u.{value}") + share * (F.col(f"v.{value}") - F.col(f"u.{value}")), F.col(f"v.{value}")).alias(value))
