"""Closed forms: space, share of neighbours in range, sums of distances by layer."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hybridrange import ranks
from hybridrange.graphs import window_pairs
from hybridrange.layers import layer_count_col


def space(n: Column, o: int, m: int) -> Column:
    """Links of all layers: each row has min(2 * o**l, m) in layer l."""
    layers = F.sequence(F.lit(0), layer_count_col(n, o) - 1)
    return n * F.aggregate(layers, F.lit(0).cast("long"), lambda s, l: s + F.least(F.lit(m), 2 * F.pow(F.lit(o), l)).cast("long"))


def space_table(rows: DataFrame, bases: list[int], m: int = 16) -> DataFrame:
    """(o, n, layers, links, bytes) for every base and size ``rows(n)``."""
    out = None
    for o in bases:
        one = rows.select(F.lit(o).alias("o"), "n", layer_count_col(F.col("n"), o).alias("layers"), space(F.col("n"), o, m).alias("links"), (F.col("n") * layer_count_col(F.col("n"), o) * m * 4).alias("slot_bytes"))
        out = one if out is None else out.union(one)
    return out


def in_range_fraction(n: Column, w: Column) -> Column:
    """Mean share of a window of half width w that a range of n rows holds, over the rows in the range, counted by place."""
    inside = F.least(n - F.lit(1), w)
    # a row at place i of n sees min(i, w) rows in range to its left and min(n - 1 - i, w) to its right
    return 2 * (inside * (inside + 1) / 2 + (n - 1 - inside) * w) / (n * 2 * w)


def printed_bounds(n: Column, o: int) -> Column:
    """The published bounds by their case, as (case, low, high)."""
    exact = F.log(float(o), n / 2)
    l = F.floor(exact + 1e-9)
    p = F.pow(F.lit(float(o)), l)
    upper = F.struct(F.lit("c").alias("case"), (0.75 - 1 / (4 * p)).alias("low"), (1 - (p + 1) / (4 * p * F.sqrt(F.lit(float(o))))).alias("high"))
    wide = F.struct(F.lit("a").alias("case"), F.lit(1 / o**0.5).alias("low"), F.lit(0.5).alias("high"))
    narrow = F.struct(F.lit("b").alias("case"), (F.lit(2**0.5 / 2) - 1 / (4 * p * o)).alias("low"), (0.75 - 1 / (4 * p * o)).alias("high"))
    return F.when(exact - l <= 0.5, upper).otherwise(wide if o > 4 else narrow)


def fraction_table(spark: SparkSession, sizes: list[int], bases: list[int]) -> DataFrame:
    """``fractions`` of given sizes."""
    return fractions(spark.createDataFrame([(x,) for x in sizes], "n long"), bases)


def fractions(rows: DataFrame, bases: list[int]) -> DataFrame:
    """(o, n, fraction, case, low, high) on the landing layer of each range size ``rows(n)``; the bounds are for ranges of two rows and more."""
    from hybridrange.layers import landing_layer_col

    out = None
    for o in bases:
        w = F.pow(F.lit(o), landing_layer_col(F.col("n"), o, F.lit(60))).cast("long")
        b = F.when(F.col("n") >= 2, printed_bounds(F.col("n"), o))
        one = rows.select(F.lit(o).alias("o"), "n", w.alias("w"), F.round(in_range_fraction(F.col("n"), w), 6).alias("fraction"), b.getField("case").alias("case"), F.round(b.getField("low"), 6).alias("low"), F.round(b.getField("high"), 6).alias("high"))
        out = one if out is None else out.union(one)
    return out


def layer_distance_sums(data: DataFrame, o: int, m: int, low: int) -> DataFrame:
    """(src, s_low, s_high, holds): sums over the same number of nearest rows in layer ``low`` and the one above."""
    from pyspark.sql import Window

    ranked = ranks.with_ranks(data)

    def nearest(layer: int, name: str) -> DataFrame:
        place = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
        return window_pairs(ranked, o, layer).withColumn("place", place).where(F.col("place") <= m).select("src", "place", F.sqrt("dist").alias(name))

    both = nearest(low, "a").join(nearest(low + 1, "b"), ["src", "place"])
    sums = both.groupBy("src").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    return sums.select("src", F.round("a", 6).alias("s_low"), F.round("b", 6).alias("s_high"), (F.col("b") <= F.col("a") + 1e-9).alias("holds"))
