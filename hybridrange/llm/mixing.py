"""Mixing sources to target weights by the cube method.

Every document of a source is taken ``floor(r)`` times, r being target over
source size, and once more with probability r - floor(r).  Those fractional
probabilities are rounded by balanced sampling: a step within the null space of
the constraints (words and number of documents) moves three documents at a time
until one of them reaches 0 or 1.  Blocks of one source are worked on in
parallel, the largest documents first; the few that a block leaves open meet in
the next round, until one block holds them.  There the last LAND ones are landed
by the best of all their roundings, and what this still owes is made up by
turning one or two documents of the block round.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C

#: Most documents of a block of the flight phase.
BLOCK = 2_000
#: Most documents that flight leaves to be landed.
LAND = 12
#: Part of a block's words that it may miss.
MISS = 0.001
#: No source is taken more often than this.
CAP = 3.0
TINY = 1e-9


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: dict[str | None, int], weights: list[float] | None = None, cap: float = CAP) -> dict[str | None, float]:
    """Words to take from each source.

    Sources by code point, null last, weigh ``weights`` in turn (1, 2, 3 if not
    given) and share all words; what exceeds ``cap`` times a source's size is
    shared again by weight among the others until none is above.
    """
    names = sorted((x for x in sizes if x is not None), key=lambda x: x.encode("utf-8")) + [None] * (None in sizes)
    w = {x: float((weights or [1, 2, 3])[i % len(weights or [1, 2, 3])]) for i, x in enumerate(names)}
    left, open_, out = float(sum(sizes.values())), list(names), {}
    while open_:
        total = sum(w[x] for x in open_)
        full = [x for x in open_ if left * w[x] / total > cap * sizes[x]]
        if not full:
            return out | {x: left * w[x] / total for x in open_}
        out |= {x: cap * sizes[x] for x in full}
        left -= sum(out[x] for x in full)
        open_ = [x for x in open_ if x not in full]
    return out


def flight(p: np.ndarray, size: np.ndarray, draw: np.random.Generator, leave: int = 2) -> np.ndarray:
    """Moves probabilities to 0 or 1, keeping the sums of p*size and of p as they are; at most two, or ``leave``, stay open."""
    p, width = p.copy(), 3
    todo = [i for i in range(len(p)) if TINY < p[i] < 1 - TINY]
    todo.reverse()
    hand: list[int] = []
    uniform = draw.random(2 * len(p) + 8)
    u = 0
    while True:
        while len(hand) < width and todo:
            hand.append(todo.pop())
        if len(hand) < width or len(hand) + len(todo) <= leave:
            return p
        s = [float(size[i]) for i in hand]
        v = [s[1] - s[2], s[2] - s[0], s[0] - s[1]]
        if not any(v):
            v = [1.0, -1.0, 0.0]
        up = min(((1 - p[i]) / x if x > 0 else -p[i] / x) for i, x in zip(hand, v, strict=True) if x)
        down = min((p[i] / x if x > 0 else (p[i] - 1) / x) for i, x in zip(hand, v, strict=True) if x)
        step = up if uniform[u] * (up + down) < down else -down
        u += 1
        if u == len(uniform):
            uniform, u = draw.random(len(uniform)), 0
        for i, x in zip(hand, v, strict=True):
            p[i] += step * x
            if p[i] <= TINY:
                p[i] = 0.0
            elif p[i] >= 1 - TINY:
                p[i] = 1.0
        hand = [i for i in hand if 0 < p[i] < 1]


def land(p: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Rounds the few open ones: of all their roundings the one nearest in words, then in number."""
    p = p.copy()
    open_ = np.flatnonzero((p > 0) & (p < 1))
    if len(open_):
        ways = (np.arange(1 << len(open_))[:, None] >> np.arange(len(open_))) & 1
        words, number = np.abs(ways @ size[open_] - p[open_] @ size[open_]), np.abs(ways.sum(1) - p[open_].sum())
        p[open_] = ways[np.lexsort((number, words))[0]]
    return p


def made_up(taken: np.ndarray, owed: float, size: np.ndarray, free: np.ndarray, within: float) -> np.ndarray:
    """Turns one or two of the ``free`` documents round at a time while that brings the words taken nearer to what is owed."""
    taken = taken.copy()
    while (gap := owed - float(taken @ size)) and abs(gap) > within:
        at = free[np.argsort((1 - 2 * taken[free]) * size[free], kind="stable")]
        change = (1 - 2 * taken[at]) * size[at]
        if not len(at):
            break
        pick = np.clip(np.searchsorted(change, gap - change), 0, len(at) - 1)
        pairs = [(abs(gap - change[i]), i, i) for i in range(len(at))]
        pairs += [(abs(gap - change[i] - change[j]), i, j) for i, k in enumerate(pick.tolist()) for j in (max(0, k - 1), k) if i != j]
        best, i, j = min(pairs)
        if best >= abs(gap):
            break
        for x in {i, j}:
            taken[at[x]] = 1 - taken[at[x]]
    return taken


def steps(seed: int, last: bool, leave: int):
    def each(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("size", "descending"), ("turn", "ascending"), ("doc_id", "ascending"), ("rid", "ascending")])
        start, size = rows["p"].to_numpy().copy(), rows["size"].to_numpy()
        draw = np.random.default_rng([seed, zlib.crc32(str(key[0].as_py()).encode()), key[1].as_py(), len(start)])
        p = flight(start, size, draw, leave)
        if last:
            owed = float(start @ size)
            p = made_up(land(p, size), owed, size, np.flatnonzero((start > TINY) & (start < 1 - TINY)), MISS * owed)
        return rows.set_column(rows.schema.get_field_index("p"), "p", pa.array(p))

    return each


def mix(docs: DataFrame, weights: list[float] | None = None, cap: float = CAP, seed: int = 7, block: int = BLOCK) -> DataFrame:
    """(rid, doc_id, size, source_size, target, copies, taken) of every row; equal on every run.

    ``rid`` numbers the rows of the scan.  Null texts have size 0, a null source
    is a source of its own, last in order; a source of size 0 has target 0 and
    takes nothing; rows that repeat a doc_id are drawn apart; an empty table
    gives no rows.  Only the sums by source reach the driver.
    """
    sized = C.cut(docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", "source", word_count(F.col("text")).alias("size")), "sized")
    by = {r["source"]: (r["s"], r["n"]) for r in sized.groupBy("source").agg(F.sum("size").alias("s"), F.count("*").alias("n")).collect()}
    goal = targets({k: v[0] for k, v in by.items()}, weights, cap)
    spark = docs.sparkSession
    ratio = {k: goal[k] / v[0] if v[0] else 0.0 for k, v in by.items()}
    plan = spark.createDataFrame([(k, v[0], goal[k], int(ratio[k] + TINY), max(0.0, ratio[k] - int(ratio[k] + TINY)), max(1, -(-v[1] // block))) for k, v in by.items()], "source string, source_size long, target double, whole long, p double, blocks long")
    joined = sized.withColumnRenamed("source", "_source").join(F.broadcast(plan), F.col("_source").eqNullSafe(F.col("source"))).drop("_source")
    open_ = joined.where(f"p > {TINY}").select("source", "rid", "doc_id", "size", "p", F.xxhash64("doc_id", F.lit(seed)).alias("turn"), "blocks")
    kind, settled = T.StructType([f for f in open_.drop("blocks").schema.fields] + [T.StructField("block", T.LongType())]), []
    most = max((v[1] for v in by.values()), default=0)
    while True:
        last = most <= block
        deal = F.lit(0).cast("long") if last else F.pmod(F.xxhash64("turn", "size"), F.col("blocks"))
        flown = C.cut(open_.withColumn("block", deal).drop("blocks").groupBy("source", "block").applyInArrow(steps(seed, last, max(2, min(LAND, block // 4))), kind), "flight")
        settled.append(flown.where("p = 0 or p = 1").select("rid", "p"))
        if last:
            break
        most = max((r["n"] for r in flown.where("p > 0 and p < 1").groupBy("source").agg(F.count("*").alias("n")).collect()), default=0)
        open_ = flown.where("p > 0 and p < 1").drop("block").withColumn("blocks", F.lit(max(1, -(-most // block))).cast("long"))
    taken = settled[0]
    for more in settled[1:]:
        taken = taken.union(more)
    out = joined.drop("p").join(taken.where("p = 1"), "rid", "left").withColumn("copies", F.col("whole") + F.coalesce(F.col("p"), F.lit(0.0)).cast("long"))
    return out.select("rid", "doc_id", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_rows(docs: DataFrame, **how) -> DataFrame:
    """The rows of the mix with the columns of ``docs``, each as often as it is taken."""
    names, docs = docs.columns, C.stable(docs)
    rid, copies, turn = (C.free(docs, x) for x in ("_rid", "_copies", "_turn"))
    drawn = mix(docs, **how).where("copies > 0").select(F.col("rid").alias(rid), F.col("copies").alias(copies))
    rows = docs.withColumn(rid, F.monotonically_increasing_id()).join(drawn, rid)
    return rows.withColumn(turn, F.explode(F.sequence(F.lit(1).cast("long"), F.col(copies)))).select(*names)


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(C.documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "copies")


QUERIES = {"op7_mixing": op7_mixing}
ORACLES: dict[str, str] = {}
