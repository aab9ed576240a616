"""Builds and searches any kind of index, one task for each segment, and the exact DataFrame forms of filtering."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hybridrange import index as X
from hybridrange import ranks
from hybridrange.baselines.kernels import KINDS, Index
from hybridrange.exact import _finished, counted_before, exact_knn, exact_range_knn, nearest_of, top_k
from hybridrange.functions.vectors import distance
from hybridrange.plans.tables import cut, small

OUT = "seg long, sub int, qid long, omega int, id long, dist double, dc long, fc long, bytes long, build_s double, search_s double"


def built_of(kind: str, part: pd.DataFrame, order: str, settings: dict) -> tuple[pd.DataFrame, Index, float]:
    """The rows of a segment as they arrive, the index over them and the seconds to build it."""
    rows = X.arrival(part, "sorted" if kind == "interval_graph" else order)
    began = time.perf_counter()
    # of a segment, the rows that are loaded first are its own even ids
    more = settings | ({"first": float((rows["id"] % 2 == 0).mean())} if "first" in settings else {})
    held = KINDS[kind](np.stack(rows["vec"].to_numpy()), rows["rank_u"].to_numpy(), **more)
    return rows, held, time.perf_counter() - began


def sizes(kind: str, data: DataFrame, order: str = "shuffled", cap: int = X.CAP, **settings) -> DataFrame:
    """(seg, sub, bytes, build_s) of an index that is built and not searched."""
    return sizes_of((kind,), data, order, cap, **settings).drop("index")


def sizes_of(kinds: tuple[str, ...], data: DataFrame, order: str = "shuffled", cap: int = X.CAP, **settings) -> DataFrame:
    """(index, seg, sub, bytes, build_s) of several kinds over the same segments, each built in full and not searched."""

    def sized(part: pd.DataFrame) -> pd.DataFrame:
        seg, sub, out = part["seg"].iloc[0], part["sub"].iloc[0], []
        for kind in kinds:
            _, held, built = built_of(kind, part, order, settings)
            out.append((kind, seg, sub, held.bytes(), built))
        return pd.DataFrame(out, columns=["index", "seg", "sub", "bytes", "build_s"])

    rows = X.segmented(data, cap).select("seg", "sub", "id", "rank_u", "vec")
    return X.dealt(rows, "seg", "sub").groupBy("seg", "sub").applyInPandas(sized, "index string, seg long, sub int, bytes long, build_s double")


def run_kind(kind: str, data: DataFrame, queries: DataFrame, k: int = 10, omegas: tuple[int, ...] = (64,), order: str = "shuffled", cap: int = X.CAP, hows: tuple[dict, ...] = (), **settings) -> DataFrame:
    """One row per query, beam width and result; costs stand on a query's first row of a segment.

    With ``hows`` one window stack is searched in each of these ways, told by their
    place in a column ``way``; queries of several sets carry their ``set``, which
    their results keep.
    """
    segs, sets = X.segmented(data, cap), "set" in queries.columns

    def searched(part: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(part):
            rows, held, built = built_of(kind, part, order, settings)
            values, codes = X.value_order(rows)
            ids, size = rows["id"].to_numpy(), held.bytes()
            seg, sub = int(rows["seg"].iloc[0]), int(rows["sub"].iloc[0])
            base = held.how if hows else None
            for q in asked.itertuples():
                bounds = X.bounds_of(values, codes, q.lo, q.hi)
                for way, omega in [(w, x) for w in range(max(1, len(hows))) for x in omegas] if bounds else ():
                    if hows:
                        held.how = base | hows[way]
                    began = time.perf_counter()
                    f = held.query(np.asarray(q.qvec, float), bounds, k, omega)
                    took = time.perf_counter() - began
                    found = list(zip([int(ids[r]) for r in f.rows], f.dist, strict=True)) or [(None, None)]
                    told = ((way,) if hows else ()) + ((q.set,) if sets else ())
                    out += [(seg, sub, q.qid, omega, i, d, *((f.dc, f.fc) if not n else (0, 0)), size, built, took if not n else 0.0, *told) for n, (i, d) in enumerate(found)]
        frame = pd.DataFrame(out, columns=[x.split()[0] for x in schema.split(", ")])
        frame["id"] = frame["id"].astype("Int64")
        return frame

    schema = OUT + ", way int" * bool(hows) + ", set int" * sets
    return X.dealt(segs, "seg", "sub").groupBy("seg", "sub").cogroup(X.dealt(X.routed(segs, queries), "in_seg", "in_sub").groupBy("in_seg", "in_sub")).applyInPandas(searched, schema)


def merged(parts: DataFrame, k: int = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """(omega, qid, id, dist) beside ``by``: the k nearest over all segments."""
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy(*by, "omega", "qid").orderBy("dist", "id"))
    return parts.where("id is not null").withColumn("pos", place).where(F.col("pos") <= k).select(*by, "omega", "qid", "id", "dist", "pos")


def postfilter_exact(data: DataFrame, queries: DataFrame, k: int = 10, alpha: float = 1.0, metric: str = "l2") -> DataFrame:
    """(qid, id, dist, pos): of each query's ceil(alpha * k / f) nearest rows those in range, cut to k."""
    n = data.count()
    counts = ranks.range_counts(ranks.order_stats(data), queries)
    fetch = F.least(F.lit(n), F.ceil(F.lit(alpha * k) * n / F.col("n_rows")))
    asked = queries.join(counts.where("n_rows > 0"), "qid").withColumn("fetch", fetch)
    if metric == "l2":
        # of the rows in range only the k nearest can be results; their places among all rows are counted
        best = cut(top_k(nearest_of(data, asked, k, True), k).where("dist is not null").select("qid", "id", "dist"), "nearest")
        places = counted_before(data.where("vec is not null"), asked, best)
        inside = best.join(places, ["qid", "id"]).join(asked.select("qid", "fetch"), "qid").where("place <= fetch")
        return _finished(inside.select("qid", "id", "dist"), k)
    from pyspark.sql import Window

    pairs = data.crossJoin(small(asked.select("qid", "qvec", "lo", "hi", "fetch")))  # a stated query set of checked size
    place = F.row_number().over(Window.partitionBy("qid").orderBy("dist", "id"))
    near = pairs.select("qid", "id", "attr", "lo", "hi", "fetch", distance(metric, "vec", "qvec").alias("dist")).withColumn("pos", place)
    inside = near.where((F.col("pos") <= F.col("fetch")) & (F.col("attr") >= F.col("lo")) & (F.col("attr") <= F.col("hi")))
    return _finished(inside.select("qid", "id", "dist"), k)


def postfilter_retry(data: DataFrame, queries: DataFrame, k: int = 10, metric: str = "l2") -> DataFrame:
    """(qid, id, dist, pos): doubles the fetch of unfinished queries until k rows are in range or the data is exhausted."""
    n = data.count()
    want = ranks.range_counts(ranks.order_stats(data), queries)
    open_, fetch, done = queries.select("qid", "qvec", "lo", "hi"), 4 * k, None
    while True:
        near = exact_knn(data.select("id", "vec"), open_, min(fetch, n), metric).select("qid", "id", "dist")
        inside = near.join(data.select("id", "attr"), "id").join(small(open_.select("qid", "lo", "hi")), "qid").where((F.col("attr") >= F.col("lo")) & (F.col("attr") <= F.col("hi")))
        found = cut(top_k(inside.select("qid", "id", "dist"), k), "retry")
        full = found.groupBy("qid").agg(F.count("*").alias("got")).join(want, "qid").where(F.col("got") >= F.least(F.lit(k), F.col("n_rows"))).select("qid")
        ready = found.join(full, "qid", "left_semi") if fetch < n else found
        done = ready if done is None else done.union(ready)
        open_ = cut(open_.join(full, "qid", "left_anti"), "open")
        if fetch >= n or open_.isEmpty():
            return done.select("qid", "id", "dist", F.col("pos").cast("int").alias("pos"))
        fetch *= 2


def adaptive_exact(data: DataFrame, queries: DataFrame, k: int = 10, share: float = 0.25) -> DataFrame:
    """Scans the range where it holds at most ``share`` of the rows, else post-filters with retries."""
    n = data.count()
    counts = ranks.range_counts(ranks.order_stats(data), queries)
    narrow = counts.where(F.col("n_rows") <= share * n).select("qid")
    return exact_range_knn(data, queries.join(narrow, "qid", "left_semi"), k).union(postfilter_retry(data, queries.join(narrow, "qid", "left_anti"), k))
