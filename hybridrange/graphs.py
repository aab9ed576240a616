"""Window graphs by joins: nearest in the window, greedy diversity, and the defining relative-neighbour rule.

Pairs within o**layer ranks meet by an equality join on blocks of that width and
their right neighbours, never by a product of all rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hybridrange import ranks
from hybridrange.functions.vectors import l2sq
from hybridrange.hybrid import l2sq_sql


def in_window(a: Column, b: Column, o: int, layer: int, strict: bool = False) -> Column:
    """Whether two ranks may be linked in a layer; ``strict`` is the literal definition."""
    gap = F.abs(a - b)
    return gap < o**layer if strict else gap <= o**layer


def window_pairs(ranked: DataFrame, o: int, layer: int, strict: bool = False) -> DataFrame:
    """(src, dst, dist, rs, rd) of all ordered pairs within the window, from rows (id, vec, rank_u)."""
    block = o**layer
    left = ranked.select(F.col("id").alias("src"), F.col("vec").alias("sv"), F.col("rank_u").alias("rs"), F.floor(F.col("rank_u") / block).alias("b"))
    near = F.explode(F.array(*[F.floor(F.col("rank_u") / block) + F.lit(i) for i in (-1, 0, 1)]))
    right = ranked.select(F.col("id").alias("dst"), F.col("vec").alias("dv"), F.col("rank_u").alias("rd"), near.alias("b"))
    pairs = left.join(right, "b").where((F.col("src") != F.col("dst")) & in_window(F.col("rs"), F.col("rd"), o, layer, strict))
    return pairs.select("src", "dst", l2sq("sv", "dv").alias("dist"), "rs", "rd")


def window_knn_graph(data: DataFrame, o: int, layer: int, m: int) -> DataFrame:
    """(src, dst, place): the m nearest rows in each row's window, without pruning."""
    place = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
    return window_pairs(ranks.with_ranks(data), o, layer).withColumn("place", place).where(F.col("place") <= m).select("src", "dst", F.col("place").cast("int").alias("place"))


def exact_window_rng(data: DataFrame, o: int, layer: int, dominators: str = "window") -> DataFrame:
    """(src, dst): pairs in the window of which no third row is nearer to both ends.

    ``window`` takes third rows from the window of the first end, ``all`` from
    every row, as the literal definition says.
    """
    ranked = ranks.with_ranks(data)
    pairs = window_pairs(ranked, o, layer).select("src", "dst", "dist")
    wide = layer
    if dominators == "all":
        n = ranked.agg(F.max("rank_u")).first()[0] or 0
        while o**wide < n:
            wide += 1
    # both sides of a triangle have to be shorter than its third; the second need not be in the window of the far end
    first = window_pairs(ranked, o, wide).select("src", F.col("dst").alias("mid"), F.col("dist").alias("a"))
    vecs = ranked.select(F.col("id").alias("mid"), F.col("vec").alias("mv"))
    far = ranked.select(F.col("id").alias("dst"), F.col("vec").alias("dv"))
    thirds = pairs.join(first, "src").where((F.col("mid") != F.col("dst")) & (F.col("a") < F.col("dist")))
    dominated = thirds.join(vecs, "mid").join(far, "dst").where(l2sq("mv", "dv") < F.col("dist")).select("src", "dst").distinct()
    return pairs.join(dominated, ["src", "dst"], "left_anti").select("src", "dst")


def diverse_graph(data: DataFrame, o: int, layer: int, cap: int) -> DataFrame:
    """(src, nbrs): candidates of the window by distance, each kept unless a kept one is nearer to it than the target is, up to ``cap``."""
    ranked = ranks.with_ranks(data)
    vecs = ranked.select(F.col("id").alias("dst"), F.col("vec").alias("dv"))
    listed = window_pairs(ranked, o, layer).join(vecs, "dst").groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst", "dv"))).alias("c"))
    start = F.filter("c", lambda x: F.lit(False))
    near = lambda kept, x: F.exists(kept, lambda y: l2sq(y["dv"], x["dv"]) < x["dist"])
    kept = F.aggregate("c", start, lambda kept, x: F.when((F.size(kept) < cap) & ~near(kept, x), F.array_append(kept, x)).otherwise(kept))
    return listed.select("src", F.transform(kept, lambda x: x["dst"]).alias("nbrs"))


def bulk_stack(data: DataFrame, o: int, m: int, layers: list[int]) -> DataFrame:
    """(layer, src, nbrs) of several layers built by joins."""
    out = None
    for layer in layers:
        one = diverse_graph(data, o, layer, m).select(F.lit(layer).alias("layer"), "src", "nbrs")
        out = one if out is None else out.union(one)
    return out


def degree_histogram(graph: DataFrame) -> DataFrame:
    """(layer, degree, n) of a graph (layer, src, nbrs)."""
    return graph.groupBy("layer", F.size("nbrs").alias("degree")).agg(F.count("*").alias("n"))


def out_of_window(edges: DataFrame, ranked: DataFrame, o: int) -> DataFrame:
    """(layer, outside): links of each layer that left their window."""
    a, b = ranked.select(F.col("id").alias("src"), F.col("rank_u").alias("rs")), ranked.select(F.col("id").alias("dst"), F.col("rank_u").alias("rd"))
    width = F.pow(F.lit(o), F.col("layer"))
    return edges.join(a, "src").join(b, "dst").groupBy("layer").agg(F.sum((F.abs(F.col("rs") - F.col("rd")) > width).cast("long")).alias("outside"))


# Oracles -----------------------------------------------------------------


def ranked_sql(name: str) -> str:
    from hybridrange.hybrid import hybrid_sql

    return f"h AS (SELECT id, vec, dense_rank() OVER (ORDER BY attr) - 1 AS r FROM ({hybrid_sql(name)}))"


def pairs_sql(name: str, o: int, layer: int) -> str:
    return f"{ranked_sql(name)}, p AS (SELECT a.id AS src, b.id AS dst, b.vec AS dv, a.r AS rs, b.r AS rd, {l2sq_sql('a.vec', 'b.vec')} AS dist FROM h a JOIN h b ON a.id <> b.id AND abs(a.r - b.r) <= {o**layer})"


def knn_graph_sql(name: str, o: int, layer: int, m: int) -> str:
    return f"WITH {pairs_sql(name, o, layer)} SELECT src, dst, CAST(place AS INTEGER) AS place FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS place FROM p) WHERE place <= {m}"


def rng_sql(name: str, o: int, layer: int) -> str:
    return f"WITH {pairs_sql(name, o, layer)} SELECT src, dst FROM p WHERE NOT EXISTS (SELECT 1 FROM p t WHERE t.src = p.src AND t.dst <> p.dst AND t.dist < p.dist AND {l2sq_sql('t.dv', 'p.dv')} < p.dist)"


def diverse_sql(name: str, o: int, layer: int, cap: int) -> str:
    fold = f"list_reduce(c, lambda kept, x: CASE WHEN len(kept) < {cap} AND NOT list_bool_or(list_concat([false], list_transform(kept, lambda y: {l2sq_sql('y.v', 'x[1].v')} < x[1].d))) THEN list_concat(kept, x) ELSE kept END, CAST([] AS STRUCT(d DOUBLE, i BIGINT, v FLOAT[])[]))"
    return f"WITH {pairs_sql(name, o, layer)}, l AS (SELECT src, list([struct_pack(d := dist, i := dst, v := dv)] ORDER BY dist, dst) AS c FROM p GROUP BY src) SELECT src, list_transform({fold}, lambda t: t.i) AS nbrs FROM l"
