"""Ranks, positions and counts over an ordered attribute, without a single-partition window.

Values are folded, range-partitioned and numbered inside their partition; the
totals of the partitions, one row each, give the offsets.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hybridrange.plans.tables import cut, width


def order_stats(df: DataFrame, attr: str = "attr") -> DataFrame:
    """(attr, mult, rank_u, before): each value's rows, the unique values below it, the rows below it.  Nulls are left out."""
    spark = df.sparkSession
    values = df.where(F.col(attr).isNotNull()).groupBy(F.col(attr).alias("attr")).agg(F.count("*").alias("mult"))
    part = cut(values.repartitionByRange(width(spark), "attr").withColumn("part", F.spark_partition_id()), "values")
    inside = Window.partitionBy("part").orderBy("attr")
    totals = part.groupBy("part").agg(F.count("*").alias("u"), F.sum("mult").alias("r"))
    other = totals.withColumnsRenamed({"part": "p2", "u": "u2", "r": "r2"})
    # one row for each partition on both sides
    offsets = totals.join(F.broadcast(other), F.col("p2") < F.col("part"), "left").groupBy("part").agg(F.coalesce(F.sum("u2"), F.lit(0)).alias("u0"), F.coalesce(F.sum("r2"), F.lit(0)).alias("r0"))
    numbered = part.withColumn("u", F.row_number().over(inside) - 1).withColumn("r", F.sum("mult").over(inside.rowsBetween(Window.unboundedPreceding, 0)) - F.col("mult"))
    return numbered.join(F.broadcast(offsets), "part").select("attr", "mult", (F.col("u") + F.col("u0")).cast("long").alias("rank_u"), (F.col("r") + F.col("r0")).cast("long").alias("before"))


def with_ranks(df: DataFrame, attr: str = "attr") -> DataFrame:
    """The rows with the rank of their value: how many unique values are below it."""
    return df.join(order_stats(df, attr).select(F.col("attr").alias("_v"), "rank_u"), F.col(attr) == F.col("_v")).drop("_v")


def with_positions(df: DataFrame, attr: str = "attr") -> DataFrame:
    """The rows (id, attr, ...) with their position in order of (attr, id)."""
    before = order_stats(df, attr).select(F.col("attr").alias("_v"), "before")
    local = df.withColumn("_in", F.row_number().over(Window.partitionBy(attr).orderBy("id")) - 1)
    return local.join(before, F.col(attr) == F.col("_v")).withColumn("pos", F.col("before") + F.col("_in")).drop("_v", "_in", "before")


def reached(values: DataFrame, points: DataFrame) -> DataFrame:
    """(pid, found): for each of ``points(pid, at, after)`` the ``found`` of the last of ``values(at, found)`` below it, or at it where ``after``.

    Both sides are dealt to ranges of ``at`` together and read once in order; what
    an empty stretch misses comes from the ranges before, one row each.
    """
    spark = values.sparkSession
    step = F.when(F.col("after"), 2).otherwise(0)
    both = values.select("at", F.lit(1).alias("step"), F.lit(None).cast(points.schema["pid"].dataType).alias("pid"), "found")
    both = both.union(points.select("at", step, "pid", F.lit(None).cast(values.schema["found"].dataType)))
    part = cut(both.repartitionByRange(width(spark), "at").withColumn("part", F.spark_partition_id()), "reached")
    ends = part.where("step = 1").groupBy("part").agg(F.max(F.struct("at", "found")).alias("end"))
    carried = part.select("part").distinct().join(F.broadcast(ends.withColumnRenamed("part", "p2")), F.col("p2") < F.col("part"), "left").groupBy("part").agg(F.max("end")["found"].alias("carry"))  # one row a partition on both sides
    last = F.last("found", ignorenulls=True).over(Window.partitionBy("part").orderBy("at", "step").rowsBetween(Window.unboundedPreceding, 0))
    return part.withColumn("last", last).where("step <> 1").join(F.broadcast(carried), "part").select("pid", F.coalesce("last", "carry").alias("found"))


def ends_of(stats: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, rows and uniques below the range's start, the same up to its end) of every query whose bounds are known."""
    held = queries.where("lo is not null and hi is not null")
    side = lambda c, after: held.select(F.struct("qid", F.lit(after).alias("end")).alias("pid"), F.col(c).alias("at"), F.lit(after).alias("after"))
    values = stats.select(F.col("attr").alias("at"), F.struct((F.col("before") + F.col("mult")).alias("r"), (F.col("rank_u") + 1).alias("u")).alias("found"))
    found = reached(values, side("lo", False).union(side("hi", True)))
    of = lambda c, end: F.coalesce(F.max(F.when(F.col("pid.end") == F.lit(end), F.col(f"found.{c}"))), F.lit(0))
    return found.groupBy(F.col("pid.qid").alias("qid")).agg(of("r", False).alias("r0"), of("u", False).alias("u0"), of("r", True).alias("r1"), of("u", True).alias("u1"))


def range_counts(stats: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, n_rows, n_uniques) in every query's closed range, by the cumulative counts at its two ends; empty ranges and those with an unknown bound count 0."""
    found = ends_of(stats, queries).select("qid", F.greatest(F.lit(0), F.col("r1") - F.col("r0")).alias("n_rows"), F.greatest(F.lit(0), F.col("u1") - F.col("u0")).alias("n_uniques"))
    return queries.select("qid").join(found, "qid", "left").select("qid", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_rows", "n_uniques")])


def value_at_rank(stats: DataFrame, wanted: Column) -> DataFrame:
    """Values whose rank satisfies a condition on ``rank_u``."""
    return stats.where(wanted)


def median_rows(stats: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, median_attr): the lower middle row's value of every range that holds one."""
    middle = ends_of(stats, queries).where("r1 > r0").select(F.col("qid").alias("pid"), F.floor((F.col("r0") + F.col("r1") - 1) / 2).cast("long").alias("at"), F.lit(True).alias("after"))
    return reached(stats.select(F.col("before").alias("at"), F.col("attr").alias("found")), middle).select(F.col("pid").alias("qid"), F.col("found").alias("median_attr"))


def window_bounds(stats: DataFrame, o: int, layer: int, strict: bool = False) -> DataFrame:
    """(attr, win_lo, win_hi): the values o**layer ranks (one less if strict) below and above, kept within the data."""
    reach = o**layer - (1 if strict else 0)
    top = stats.agg(F.max("rank_u")).first()[0] or 0
    low = stats.select(F.col("rank_u").alias("low"), F.col("attr").alias("win_lo"))
    high = stats.select(F.col("rank_u").alias("high"), F.col("attr").alias("win_hi"))
    want = stats.select("attr", F.greatest(F.lit(0), F.col("rank_u") - reach).alias("low"), F.least(F.lit(top), F.col("rank_u") + reach).alias("high"))
    return want.join(low, "low").join(high, "high").select("attr", "win_lo", "win_hi")
