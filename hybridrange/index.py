"""The window stack as a table of segments.

A segment is a run of consecutive values, with all rows of a value; a value with
more rows than the cap is dealt to sub-segments that are all searched.  Building
runs once for each segment.  An index is searched as ``packed`` stores it, one row
a segment: its bounds prune, the asked queries come to it, and only results move.
"""

from __future__ import annotations

from bisect import bisect_right
from dataclasses import asdict

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hybridrange import ranks
from hybridrange.exact import DIGITS, blocks, top_k
from hybridrange.kernel.stack import Settings, Stack
from hybridrange.layers import top_layer
from hybridrange.plans.tables import small, width

#: Rows of a segment.  A beam of fixed width loses recall as its graph grows and a
#: segment is one task, so segments stay this small and an index grows by their number.
CAP = 500


def segmented(data: DataFrame, cap: int = CAP) -> DataFrame:
    """The rows (id, vec, attr, and whatever else they carry) with seg and sub; null attributes are never in a range and are left out."""
    more = [c for c in data.columns if c not in ("seg", "sub", "id", "attr", "rank_u", "vec")]
    stats = ranks.order_stats(data).select(F.col("attr").alias("_v"), "rank_u", F.floor(F.col("before") / cap).cast("long").alias("seg"), F.ceil(F.col("mult") / cap).alias("_n"))
    rows = data.join(stats, F.col("attr") == F.col("_v"))
    return rows.withColumn("sub", F.pmod(F.xxhash64("id"), F.col("_n")).cast("int")).select("seg", "sub", "id", "attr", "rank_u", "vec", *more)


def arrival(rows: pd.DataFrame, order: str) -> pd.DataFrame:
    """``sorted`` by attribute, ``shuffled`` by a hash of the id, ``halves`` by that hash, even ids first."""
    if order == "sorted":
        return rows.sort_values(["rank_u", "id"], ignore_index=True)
    key = (rows["id"].to_numpy().astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)
    half = (rows["id"].to_numpy() % 2) * (order == "halves")
    return rows.iloc[np.lexsort((rows["id"], key, half))].reset_index(drop=True)


#: Tasks of segments to one of a shuffle, and up to how many in all.  A hash deals segments unevenly; with few in a task no core waits long for another.
TASKS, MOST_TASKS = 8, 128


def dealt(rows: DataFrame, *keys: str) -> DataFrame:
    """Rows by segment in more tasks than a narrow shuffle has: a segment's work is in its rows, not in their bytes, by which tasks would be put together."""
    n = width(rows.sparkSession)
    return rows.repartition(max(n, min(TASKS * n, MOST_TASKS)), *keys)


def build_index(data: DataFrame, settings: Settings | None = None, order: str = "shuffled", cap: int = CAP) -> DataFrame:
    """(seg, sub, ord, id, attr, rank_u, vec, deleted, links): one row per point with its links by layer.

    An index has the layers that all its unique values ask for.  Those wider than a
    segment start as copies of the one below, as every layer does when it is added.
    """
    rows, given = segmented(data, cap), asdict(settings or Settings())
    layers = given["layers"] or top_layer(max(1, data.select(F.countDistinct("attr")).first()[0]), given["o"]) + 1
    schema = T.StructType([*rows.schema.fields, T.StructField("ord", T.IntegerType()), T.StructField("deleted", T.BooleanType()), T.StructField("links", T.ArrayType(T.ArrayType(T.IntegerType())))])

    def built(part: pd.DataFrame) -> pd.DataFrame:
        part = arrival(part, order)
        stack = Stack(np.stack(part["vec"].to_numpy()), part["rank_u"].to_numpy(), Settings(**given)).build()
        while len(stack.links) < layers:
            stack.links.append(stack.links[-1])
        part["ord"], part["deleted"] = np.arange(len(part), dtype=np.int32), False
        part["links"] = [[layer[i] for layer in stack.links] for i in range(len(part))]
        return part

    return dealt(rows, "seg", "sub").groupBy("seg", "sub").applyInPandas(built, schema)


def restored(part: pd.DataFrame, settings: Settings) -> tuple[Stack, pd.DataFrame]:
    """A stack from its stored rows."""
    part = part.sort_values("ord", ignore_index=True)
    stack = Stack(np.stack(part["vec"].to_numpy()), part["rank_u"].to_numpy(), settings)
    stack.links = [[list(map(int, row[layer])) for row in part["links"]] for layer in range(len(part["links"].iloc[0]))]
    stack.deleted = part["deleted"].to_numpy(bool).copy()
    known(stack, part["rank_u"].to_numpy())
    return stack, part


def known(stack: Stack, codes: np.ndarray) -> None:
    """Tells a stack the values of rows whose links it has, all at once where its set of values can."""
    order = np.lexsort((np.arange(len(codes)), codes))
    values, heads = np.unique(codes[order], return_index=True)
    if hasattr(stack.values, "fill"):
        stack.values.fill(values.tolist())
    else:
        for v in values.tolist():
            stack.values.insert(v)
    stack.at_value = {v: x.tolist() for v, x in zip(values.tolist(), np.split(order, heads[1:]), strict=True)}
    stack.there[: len(codes)] = True
    stack.count = len(codes)


PACKED = ("seg", "sub", "attr_lo", "attr_hi", "n_rows", "payload")


def packed(index: DataFrame) -> DataFrame:
    """(seg, sub, attr_lo, attr_hi, n_rows, payload): one row a segment, its rows in Arrow's own format."""
    of = {f.name: f for f in index.schema.fields}
    schema = T.StructType([of["seg"], of["sub"], T.StructField("attr_lo", of["attr"].dataType), T.StructField("attr_hi", of["attr"].dataType), T.StructField("n_rows", T.LongType()), T.StructField("payload", T.BinaryType())])

    def wrapped(rows: pa.Table) -> pa.Table:
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, rows.schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as out:
            out.write_table(rows)
        ends = pc.min_max(rows["attr"])
        one = {"seg": rows["seg"][0], "sub": rows["sub"][0], "attr_lo": ends["min"], "attr_hi": ends["max"], "n_rows": len(rows), "payload": sink.getvalue().to_pybytes()}
        return pa.table({k: pa.array([v.as_py() if isinstance(v, pa.Scalar) else v], rows.schema.field({"attr_lo": "attr", "attr_hi": "attr"}.get(k, k)).type if k in ("seg", "sub", "attr_lo", "attr_hi") else None) for k, v in one.items()})

    return dealt(index, "seg", "sub").groupBy("seg", "sub").applyInArrow(wrapped, schema)


def unpacked(payload: bytes) -> pd.DataFrame:
    """The rows of one segment; times come without their zone, as the rows of an index are handed to Python."""
    rows = pa.ipc.open_stream(payload).read_all()
    at = rows.schema.get_field_index("attr")
    if pa.types.is_timestamp(rows.schema.field(at).type):
        rows = rows.set_column(at, "attr", rows["attr"].cast(pa.timestamp("ns")))
    return rows.to_pandas()


def bounds_of(values: np.ndarray, codes: np.ndarray, low, high) -> tuple[int, int] | None:
    """Codes of the first and last value within [low, high]; ``values`` ascend."""
    if values.dtype.kind == "M":
        low, high = np.datetime64(low), np.datetime64(high)
    a, b = int(np.searchsorted(values, low, "left")), int(np.searchsorted(values, high, "right")) - 1
    return (int(codes[a]), int(codes[b])) if a <= b else None


def value_order(part: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    unique = part.drop_duplicates("rank_u").sort_values("rank_u")
    return unique["attr"].to_numpy(), unique["rank_u"].to_numpy()


def routed(index: DataFrame, queries: DataFrame) -> DataFrame:
    """The queries with every segment that their range meets."""
    segments = index.groupBy(F.col("seg").alias("in_seg"), F.col("sub").alias("in_sub")).agg(F.min("attr").alias("attr_lo"), F.max("attr").alias("attr_hi"))
    meets = (F.col("lo") <= F.col("attr_hi")) & (F.col("hi") >= F.col("attr_lo"))
    return queries.join(small(segments), meets).select("in_seg", "in_sub", "qid", "qvec", "lo", "hi", *[c for c in queries.columns if c == "set"])


PART = "qid long, id long, dist double, dc long, fc long, scanned boolean, seen long, passed long, hops array<array<int>>"


def asked_of(parts: DataFrame, queries: DataFrame) -> DataFrame:
    """``parts`` that a query's range meets, with these queries as an array: bounds prune the parts, and one row with all queries is sent to them."""
    low, high = queries.agg(F.min("lo"), F.max("hi")).first()
    met = parts.where((F.col("attr_hi") >= F.lit(low)) & (F.col("attr_lo") <= F.lit(high))) if low is not None and high is not None else parts
    every = queries.where("lo <= hi").agg(F.collect_list(F.struct("qid", "qvec", "lo", "hi")).alias("every"))
    mine = F.filter("every", lambda q: (q["lo"] <= F.col("attr_hi")) & (q["hi"] >= F.col("attr_lo")))
    return met.crossJoin(F.broadcast(every)).withColumn("asked", mine).drop("every").where(F.size("asked") > 0)  # one row on the other side


def search(index: DataFrame, queries: DataFrame, k: int = 10, omega: int = 64, settings: Settings | None = None, second: tuple | None = None, **how) -> DataFrame:
    """One row per query, segment and row found there; a query that finds nothing in a segment has a row without id.

    ``index`` is as ``packed`` gives it, or as built, which is packed first.  The
    queries are a stated set; beyond exact.QUERY_BYTES they are asked in blocks.  With
    ``second = (column, low, high)`` rows outside these bounds are walked and not
    returned.
    """
    given = asdict(settings or Settings())
    parts = index if "payload" in index.columns else packed(index)

    def searched(batches):
        for batch in batches:
            out = []
            for payload, asked in zip(batch["payload"], batch["asked"], strict=True):
                stack, part = restored(unpacked(payload), Settings(**given))
                values, codes = value_order(part)
                ids = part["id"].to_numpy()
                hidden = None if second is None else ~part[second[0]].between(second[1], second[2]).to_numpy(bool)
                for q in asked:
                    bounds = bounds_of(values, codes, q["lo"], q["hi"])
                    if bounds is None:
                        continue
                    f = stack.query(np.asarray(q["qvec"], float), bounds, k, omega, hidden=hidden, **how)
                    rows = list(zip([int(ids[r]) for r in f.rows], f.dist, strict=True)) or [(None, None)]
                    out += [(q["qid"], i, d, f.dc if not n else 0, f.fc if not n else 0, f.scanned, f.in_range[1] if not n else 0, f.in_range[0] if not n else 0, [list(x) for x in f.hops] if not n else []) for n, (i, d) in enumerate(rows)]
            frame = pd.DataFrame(out, columns=["qid", "id", "dist", "dc", "fc", "scanned", "seen", "passed", "hops"])
            frame["id"] = frame["id"].astype("Int64")
            yield frame

    found = None
    for block in blocks(queries):
        one = asked_of(parts, block).select("payload", "asked").mapInPandas(searched, PART)
        found = one if found is None else found.union(one)
    return found


def range_knn(index: DataFrame, queries: DataFrame, k: int = 10, omega: int = 64, settings: Settings | None = None, **how) -> DataFrame:
    """(qid, id, dist, pos): the k nearest rows in each range, merged over segments."""
    found = search(index, queries, k, omega, settings, **how).where("id is not null")
    return top_k(found.select("qid", "id", "dist"), k).select("qid", "id", F.round("dist", DIGITS).alias("dist"), F.col("pos").cast("int").alias("pos"))


def costs(parts: DataFrame) -> DataFrame:
    """(qid, dc, fc) summed over segments."""
    return parts.groupBy("qid").agg(F.sum("dc").alias("dc"), F.sum("fc").alias("fc"))


def delete(index: DataFrame, ids: DataFrame) -> DataFrame:
    """Marks rows: they are walked through and never returned."""
    gone = ids.select(F.col("id").alias("_gone")).distinct()
    return index.join(gone, F.col("id") == F.col("_gone"), "left").withColumn("deleted", F.col("deleted") | F.col("_gone").isNotNull()).drop("_gone")


def update(index: DataFrame, changed: DataFrame, settings: Settings | None = None) -> DataFrame:
    """The index with the rows of ``changed`` (id, vec, attr) in place of those of the same ids: these are marked, the new ones inserted."""
    return insert(delete(index, changed), changed, settings)


def edges(index: DataFrame) -> DataFrame:
    """(seg, sub, layer, src, dst) of all links, by number in the segment."""
    by_layer = index.select("seg", "sub", F.col("ord").alias("src"), F.posexplode("links").alias("layer", "to"))
    return by_layer.select("seg", "sub", "layer", "src", F.explode("to").alias("dst"))


def insert(index: DataFrame, data: DataFrame, settings: Settings | None = None, order: str = "shuffled") -> DataFrame:
    """The index with the rows of ``data`` (id, vec, attr) inserted one by one into the segments they belong to.

    A row goes to the last segment that starts at or below its value, or to the
    first, found by bisection of the segments' starts; of the sub-segments of a
    common value to that which its id picks.  Only segments that rows arrive in change; codes are renewed inside a
    segment, links stay.
    """
    given = asdict(settings or Settings())
    starts = index.groupBy(F.col("seg").alias("in_seg")).agg(F.min("attr").alias("start"), (F.max("sub") + 1).alias("n")).orderBy("start").collect()  # one row a segment
    first, own, subs = [r["start"] for r in starts], [r["in_seg"] for r in starts], [r["n"] for r in starts]

    @F.pandas_udf("in_seg long, n int")
    def home(attr: pd.Series) -> pd.DataFrame:
        at = [max(0, bisect_right(first, x.to_pydatetime() if isinstance(x, pd.Timestamp) else x) - 1) for x in attr]
        return pd.DataFrame({"in_seg": [own[i] for i in at], "n": [subs[i] for i in at]})

    routed_rows = data.where("attr is not null").withColumn("home", home("attr")).select("home.in_seg", F.pmod(F.xxhash64("id"), F.col("home.n")).cast("int").alias("in_sub"), "id", "attr", "vec")
    schema = index.schema

    def grown(part: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        if not len(new):
            return part
        old = part.sort_values("ord", ignore_index=True)
        new = new.rename(columns={"in_seg": "seg", "in_sub": "sub"})
        both = pd.concat([old[["seg", "sub", "id", "attr", "vec", "deleted"]], new.assign(deleted=False)], ignore_index=True)
        _, codes = np.unique(both["attr"].to_numpy(), return_inverse=True)
        both["rank_u"] = codes
        stack = Stack(np.stack(both["vec"].to_numpy()), codes, Settings(**given))
        stack.links = [[[int(r) for r in row[layer]] for row in old["links"]] for layer in range(len(old["links"].iloc[0]))]
        stack.deleted[: len(old)] = old["deleted"].to_numpy(bool)
        known(stack, codes[: len(old)])
        places = np.arange(len(old), len(both))
        ids = both["id"].to_numpy()[places].astype(np.uint64)
        key = codes[places] if order == "sorted" else (ids * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)
        # rows are numbered in order of arrival, as their links are
        turn = np.concatenate([np.arange(len(old)), places[np.lexsort((ids, key))]])
        both = both.iloc[turn].reset_index(drop=True)
        stack.vecs, stack.codes, stack.deleted, stack.there = stack.vecs[turn], stack.codes[turn], stack.deleted[turn], stack.there[turn]
        stack.code_of = stack.codes.tolist()
        for row in range(len(old), len(both)):
            stack.insert(row)
        both["ord"] = np.arange(len(both), dtype=np.int32)
        both["links"] = [[layer[i] for layer in stack.links] for i in range(len(both))]
        return both[[f.name for f in schema.fields]]

    return dealt(index, "seg", "sub").groupBy("seg", "sub").cogroup(dealt(routed_rows, "in_seg", "in_sub").groupBy("in_seg", "in_sub")).applyInPandas(grown, schema)


def split(index: DataFrame, cap: int, settings: Settings | None = None) -> DataFrame:
    """Segments of more than ``cap`` rows are cut at a value and linked anew, so that no link is merely dropped; the others stay."""
    large = index.groupBy(F.col("seg").alias("s")).agg(F.count("*").alias("n"), F.countDistinct("attr").alias("u")).where((F.col("n") > cap) & (F.col("u") > 1))
    over = index.join(small(large.select("s")), F.col("seg") == F.col("s"), "left_semi")
    last = index.agg(F.max("seg")).first()[0] or 0
    renewed = build_index(over.where("not deleted").select("id", "vec", "attr"), settings, cap=max(1, cap // 2))
    return index.join(small(large.select("s")), F.col("seg") == F.col("s"), "left_anti").unionByName(renewed.withColumn("seg", F.col("seg") + last + 1))


def level_search(index: DataFrame, queries: DataFrame, k: int = 10, omega: int = 64, rounds: int = 50) -> DataFrame:
    """(qid, id, dist, pos) by a beam that opens all its unopened rows at once, as joins: no Python in the loop.

    Each round joins the open rows' links on all layers, keeps what is in range
    and new, and cuts the best ``omega`` of each query; it ends when a round opens
    nothing.  Every segment's middle row in range is an entry.
    """
    from pyspark.sql import Window

    from hybridrange.functions.vectors import distance
    from hybridrange.plans.tables import cut

    rows = index.select("seg", "sub", "ord", "id", "attr", "vec")
    links = edges(index).select("seg", "sub", F.col("src").alias("ord"), "dst").distinct()
    q = small(queries.select("qid", "qvec", "lo", "hi"))
    inside = rows.join(q, F.col("attr").between(F.col("lo"), F.col("hi")))
    middle = Window.partitionBy("qid", "seg", "sub").orderBy("attr", "id")
    entry = inside.withColumn("r", F.row_number().over(middle)).withColumn("n", F.count("*").over(Window.partitionBy("qid", "seg", "sub"))).where("r = floor((n + 1) / 2)")
    beam = cut(entry.select("qid", "seg", "sub", "ord", "id", distance("l2", "vec", "qvec").alias("dist"), F.lit(False).alias("opened")), "beam")
    best = Window.partitionBy("qid", "seg", "sub").orderBy("dist", "id")
    for _ in range(rounds):
        open_ = beam.where("not opened")
        if open_.isEmpty():
            break
        near = open_.select("qid", "seg", "sub", "ord").join(links, ["seg", "sub", "ord"]).select("qid", "seg", "sub", F.col("dst").alias("ord")).distinct()
        fresh = near.join(beam.select("qid", "seg", "sub", "ord"), ["qid", "seg", "sub", "ord"], "left_anti").join(rows, ["seg", "sub", "ord"]).join(q, "qid").where(F.col("attr").between(F.col("lo"), F.col("hi")))
        found = fresh.select("qid", "seg", "sub", "ord", "id", distance("l2", "vec", "qvec").alias("dist"), F.lit(False).alias("opened"))
        both = beam.withColumn("opened", F.lit(True)).unionByName(found)
        beam = cut(both.withColumn("r", F.row_number().over(best)).where(F.col("r") <= omega).drop("r"), "beam")
    return top_k(beam.select("qid", "id", "dist"), k).select("qid", "id", F.round("dist", DIGITS).alias("dist"), F.col("pos").cast("int").alias("pos"))
