"""SimHash near-dedup by tiled exact comparison.

A text's fingerprint takes, bit by bit, the majority over the XXH64 hashes of
its word shingles.  Distinct fingerprints are packed into tiles that share the
population counts of their segments; the difference of two population counts
bounds the Hamming distance from below, so tile pairs that differ beyond the
radius never meet.  A pair of tiles is compared in full with exclusive-or and
bit counts, and yields a spanning forest of its links rather than all pairs, so
a clique of copies stays linear in size and no link between texts is lost.

The pipeline's stage takes such links, at a wide radius, for candidates only:
the Jaccard similarity of the shingle sets decides.
"""

from __future__ import annotations

from itertools import product
from math import acos, ceil, log, pi, sqrt

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

SEED = 42
#: Fingerprints in a tile: 4 KB of ids and words for one lane.
TILE = 512
#: Seeds that turn one shingle hash into further independent lanes.
STEP = 0x9E3779B97F4A7C15


def shingle_hashes(text: bytes, k: int) -> np.ndarray:
    """XXH64 (seed 42) of each k-word shingle, repeats included; the whole sequence if it is shorter."""
    w = C.words(text)
    if not w:
        return np.empty(0, np.uint64)
    joined, xxh = b" ".join(w), xxhash.xxh64_intdigest
    if len(w) <= k:
        return np.array([xxh(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    return np.array([xxh(joined[s:e], SEED) for s, e in zip(starts[: len(w) - k + 1].tolist(), ends[k - 1 :].tolist(), strict=True)], np.uint64)


def mixed(h: np.ndarray, lane: int) -> np.ndarray:
    """Lane 0 is the hash itself; the others are bijective scrambles of it."""
    if lane == 0:
        return h
    with np.errstate(over="ignore"):
        x = h + np.uint64(STEP * lane % 2**64)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def fingerprint(h: np.ndarray, lanes: int = 1) -> list[int]:
    """Bits set in over half of the hashes, as one signed word per lane; zero for no hashes."""
    out = []
    for lane in range(lanes):
        counts, x = np.zeros(64, np.int64), np.ascontiguousarray(mixed(h, lane))
        for at in range(0, len(x), 32768):
            part = x[at : at + 32768]
            counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        out.append(int(np.packbits(counts * 2 > len(h), bitorder="little").view(np.int64)[0]))
    return out


def fingerprints(docs: DataFrame, k: int = 3, lanes: int = 1) -> DataFrame:
    """(doc_id, f0, f1, ...) of every row; null counts as empty, and a text without words gets zeros."""

    def make():
        def each(batch: pa.RecordBatch) -> dict:
            found = [fingerprint(shingle_hashes(x, k), lanes) for x in batch["text"].to_pylist()]
            return {"doc_id": batch["doc_id"]} | {f"f{i}": [x[i] for x in found] for i in range(lanes)}

        return each

    return C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), make, "doc_id long, " + ", ".join(f"f{i} long" for i in range(lanes)))


def packed(lanes: int):
    """Packs runs of one (key, salt) of a sorted partition into tiles of at most TILE fingerprints."""
    held: dict = {"key": None, "rows": []}

    def tile() -> tuple | None:
        rows, held["rows"] = held["rows"], []
        return (*held["key"], np.concatenate(rows).tobytes()) if rows else None

    def each(batch: pa.RecordBatch | None) -> dict | None:
        out = []
        if batch is None:
            out.append(tile())
        else:
            keys = list(zip(batch["key"].to_pylist(), batch["salt"].to_pylist(), strict=True))
            data = np.stack([batch[c].to_numpy(zero_copy_only=False).astype(np.int64) for c in ["rep", *(f"f{i}" for i in range(lanes))]], 1)
            at = 0
            while at < len(keys):
                end = at
                while end < len(keys) and keys[end] == keys[at]:
                    end += 1
                if keys[at] != held["key"]:
                    out.append(tile())
                    held["key"] = keys[at]
                while at < end:
                    room = TILE - sum(map(len, held["rows"]))
                    part = data[at : min(end, at + room)]
                    held["rows"].append(part)
                    at += len(part)
                    if len(part) == room:
                        out.append(tile())
        out = [x for x in out if x]
        return {"key": [x[0] for x in out], "salt": [x[1] for x in out], "blob": [x[2] for x in out]} if out else None

    return each


def close(a: np.ndarray, b: np.ndarray, same: bool, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids of the rows of two tiles within ``radius`` bits over all lanes."""
    x, y = a[:, 1:].view(np.uint64), b[:, 1:].view(np.uint64)
    gap = np.bitwise_count(x[:, None, 0] ^ y[None, :, 0])
    for lane in range(1, x.shape[1]):
        gap += np.bitwise_count(x[:, None, lane] ^ y[None, :, lane])  # 256 wraps to 0, which the full sums below put right
    i, j = np.divmod(np.flatnonzero(gap <= radius), len(y))
    if same:
        i, j = i[i < j], j[i < j]
    if x.shape[1] > 1 and len(i):
        keep = np.bitwise_count(x[i] ^ y[j]).sum(1, dtype=np.int64) <= radius
        i, j = i[keep], j[keep]
    return a[i, 0], b[j, 0]


def compared(lanes: int, radius: int):
    """Compares tile pairs; gives a spanning forest of the links found since the last one given."""
    held: list = []

    def each(batch: pa.RecordBatch | None) -> dict | None:
        if batch is not None:
            shape = lambda x: np.frombuffer(x, np.int64).reshape(-1, lanes + 1)
            for left, right, same in zip(batch["left"].to_pylist(), batch["right"].to_pylist(), batch["same"].to_pylist(), strict=True):
                a, b = close(shape(left), shape(right), same, radius)
                if len(a):
                    held.append(np.stack([a, b]))
        if not held or batch is not None and sum(x.shape[1] for x in held) < 200_000:
            return None
        both = np.concatenate(held, 1)
        held[:] = []
        child, root = C.forest(both[0], both[1])
        if batch is not None and len(child) < 100_000:  # held as stars till the input ends
            held.append(np.stack([child, root]))
            return None
        return {"a": child, "b": root}

    return each


def offsets(segments: int, bin_width: int, radius: int, sized: bool = False) -> list[tuple[int, ...]]:
    """Half of the steps between tiles whose population counts may be within the radius, zero included; with ``sized`` the first step is to the next bin of sizes."""
    least = lambda d: (abs(d) - 1) * bin_width + 1 if d else 0
    reach = min(ceil(radius / bin_width), 64 // segments // bin_width)
    every = [d for d in product(range(-reach, reach + 1), repeat=segments) if sum(map(least, d)) <= radius]
    half = [d for d in every if d >= (0,) * segments]
    return [(0, *d) for d in half] + [(1, *d) for d in every] if sized else half


def near_links(prints: DataFrame, radius: int, lanes: int = 1, segments: int = 4, bin_width: int = 1, salts: int | None = None, sized: bool = False, cell: int = 32) -> DataFrame:
    """Spanning links (a, b) of all fingerprints ``prints(rep, f0, ...)`` within ``radius`` bits.

    Tiles are keyed by the population counts of ``segments`` parts of the first
    lane, in bins; ``salts`` deals the tiles of one key out further, by default
    as the fullest key asks, without end.  With ``sized`` only tiles whose column
    ``size_bin`` is equal or next to each other meet.
    """
    spark, size = prints.sparkSession, 64 // segments
    mask = F.lit((1 << size) - 1 if size < 64 else -1).cast("long")
    base = 64 // bin_width + 2
    key = sum((F.floor(F.bit_count(F.shiftrightunsigned("f0", size * i).bitwiseAND(mask)) / bin_width) + 1) * base ** (segments - 1 - i) for i in range(segments)).cast("long")
    if sized:
        key = (F.col("size_bin") * base**segments + key).cast("long")
    if salts is None:
        most = prints.groupBy(key.alias("key")).count().agg(F.max("count")).first()[0] or 0
        salts = max(1, min(16, most // (cell * TILE)), -(-most // (256 * TILE)))
    keyed = prints.withColumns({"key": key, "salt": F.pmod(F.xxhash64("rep"), F.lit(salts)).cast("int")})
    tiles = C.cut(C.map_rows(keyed.repartition(C.width(spark), "key", "salt").sortWithinPartitions("key", "salt", "rep"), lambda: packed(lanes), "key long, salt int, blob binary", flush=True), "tiles")
    widths = [base ** (segments - 1 - i) for i in range(-sized, segments)]
    steps = [(sum(x * w for x, w in zip(d, widths, strict=True)), not any(d)) for d in offsets(segments, bin_width, radius, sized)]
    ident = F.xxhash64("blob")
    home = tiles.select("key", "salt", F.col("blob").alias("left"), ident.alias("li"))
    deal = F.array(*[F.struct(F.lit(s).cast("long").alias("step"), F.lit(z).alias("zero"), F.lit(i).alias("salt")) for s, z in steps for i in range(salts)])
    guest = tiles.select("blob", ident.alias("ri"), F.col("key").alias("own"), F.explode(deal).alias("d")).select((F.col("own") + F.col("d.step")).alias("key"), F.col("d.salt").alias("salt"), F.col("d.zero").alias("zero"), F.col("blob").alias("right"), "ri")
    pairs = home.join(guest, ["key", "salt"]).where(~F.col("zero") | (F.col("li") <= F.col("ri")))
    return C.map_rows(pairs.select("left", "right", (F.col("zero") & (F.col("li") == F.col("ri"))).alias("same")), lambda: compared(lanes, radius), "a long, b long", flush=True)


def near_groups(docs: DataFrame, k: int = 3, radius: int = 3, **how) -> DataFrame:
    """(doc_id, f0, ..., component_id) of every row: the smallest doc_id reachable over fingerprints within ``radius`` bits.

    Equal fingerprints are one node, so exact copies never multiply.  Null texts
    count as empty, texts without words have fingerprint zero and link like any
    other, rows that repeat a doc_id get a row each, an empty table gives none.
    """
    lanes = how.get("lanes", 1)
    names = [f"f{i}" for i in range(lanes)]
    each = C.cut(fingerprints(docs, k, lanes), "prints")
    distinct = C.cut(each.groupBy(*names).agg(F.min("doc_id").alias("rep")), "distinct")
    # a row that repeats a doc_id with another text makes two nodes of one name: they are then one component, as one document
    with C.rows_per_batch(docs.sparkSession, 200):
        found = C.components(near_links(distinct.where("rep is not null"), radius, **how))
    named = distinct.join(found.withColumnRenamed("node", "rep"), "rep", "left").select(*names, F.coalesce("component", "rep").alias("component_id"))
    return each.join(named, names)


def radius_for(similarity: float, bits: int) -> int:
    """Bits by which two texts of this Jaccard similarity differ on average, by the angle between their shingle counts."""
    return round(bits * acos(2 * similarity / (1 + similarity)) / pi)


#: The near-dedup of the pipeline: five-word shingles and four lanes, whose radius is too wide for population counts to part tiles; sizes do.
LANES = 4
WIDE = {"k": 5, "lanes": LANES, "segments": 1, "bin_width": 65, "sized": True, "cell": 8}


def wide_radius(similarity: float = 0.8, room: float = 1.0) -> int:
    bits = 64 * LANES
    p = radius_for(similarity, bits) / bits
    return radius_for(similarity, bits) + round(room * sqrt(bits * p * (1 - p)))


#: Deviations of room under which texts become candidates; each link between candidates is then verified.
ROOM = 4.0
#: Members of a family that are compared with each other at once.
BLOCK = 256
#: Shingles counted at once.
COLUMNS = 8192


def size_bin(size: Column, similarity: float) -> Column:
    """Sets of this similarity differ in size by a factor of 1 / similarity at most, hence by one bin."""
    return F.when(size > 0, F.floor(F.log(size.cast("double")) / -log(similarity) + 1e-9)).otherwise(-2).cast("int")


def sets(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, content, shingles, f0, ...): the distinct shingle hashes in order, a name for them, and their fingerprint."""

    def make():
        def each(batch: pa.RecordBatch) -> dict:
            found = [np.unique(shingle_hashes(x, k)) for x in batch["text"].to_pylist()]
            prints = [fingerprint(x, LANES) for x in found]
            blobs = [x.tobytes() for x in found]
            return {"doc_id": batch["doc_id"], "content": [xxhash.xxh128_digest(x) for x in blobs], "shingles": blobs} | {f"f{i}": [x[i] for x in prints] for i in range(LANES)}

        return each

    return C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), make, "doc_id long, content binary, shingles binary, " + ", ".join(f"f{i} long" for i in range(LANES)))


def shared_counts(x: list[np.ndarray], y: list[np.ndarray]) -> np.ndarray:
    """Numbers of common elements of every set of x with every set of y."""
    one, two = np.concatenate(x), np.concatenate(y)
    both = np.intersect1d(one, two)
    place = []
    for flat, parts in ((one, x), (two, y)):
        at = np.searchsorted(both, flat)
        row = np.repeat(np.arange(len(parts)), [len(p) for p in parts])
        hit = both[np.minimum(at, len(both) - 1)] == flat if len(both) else np.zeros(len(flat), bool)
        order = np.argsort(at[hit], kind="stable")
        place.append((row[hit][order], at[hit][order]))
    out = np.zeros((len(x), len(y)), np.int64)
    for low in range(0, len(both), COLUMNS):
        wide = min(COLUMNS, len(both) - low)
        tables = []
        for (row, at), parts in zip(place, (x, y), strict=True):
            table = np.zeros((len(parts), wide), np.float32)
            s, e = np.searchsorted(at, [low, low + wide])
            table[row[s:e], at[s:e] - low] = 1
            tables.append(table)
        out += (tables[0] @ tables[1].T).astype(np.int64)
    return out


def alike(similarity: float):
    """Compares the two blocks of each (family, i, j) of a sorted partition in full; gives a spanning forest of the links."""
    held: dict = {"key": None, "rows": []}

    def links() -> list[np.ndarray]:
        rows, held["rows"] = held["rows"], []
        if len(rows) < 2:
            return []
        _, i, j = held["key"]
        left = [r for r in rows if r[0] == i]
        right = left if i == j else [r for r in rows if r[0] == j]
        if not left or not right:
            return []
        x, y = ([np.frombuffer(r[2], np.uint64) for r in side] for side in (left, right))
        shared = shared_counts(x, y)
        whole = np.array([len(v) for v in x])[:, None] + np.array([len(v) for v in y])[None, :] - shared
        a, b = np.nonzero((shared / np.maximum(whole, 1) >= similarity) | (whole == 0))
        ids = [np.array([r[1] for r in side], np.int64) for side in (left, right)]
        a, b = ids[0][a], ids[1][b]
        a, b = a[a != b], b[a != b]
        return [np.stack(C.forest(a, b))] if len(a) else []

    def each(batch: pa.RecordBatch | None) -> dict | None:
        out: list[np.ndarray] = []
        if batch is None:
            out += links()
        else:
            for *key, block, rep, blob in zip(*(batch[c].to_pylist() for c in ("family", "i", "j", "block", "rep", "shingles")), strict=True):
                if key != held["key"]:
                    out += links()
                    held["key"] = key
                held["rows"].append((block, rep, blob))
        if not out:
            return None
        both = np.concatenate(out, 1)
        return {"a": both[0], "b": both[1]}

    return each


def verified(docs: DataFrame, families: DataFrame, similarity: float, k: int, block: int) -> DataFrame:
    """Spanning links (a, b) of all pairs within the families ``families(node, component)`` whose shingle sets are ``similarity`` alike.

    Members of a family are dealt to blocks, and every pair of blocks is a unit
    of work of its own, so that a large family is shared out.
    """
    spark = docs.sparkSession
    sizes = families.groupBy("component").agg(F.ceil(F.count("*") / block).cast("int").alias("n"))
    members = families.join(sizes, "component").select(F.col("node").alias("doc_id"), F.col("component").alias("family"), "n", F.pmod(F.xxhash64("node"), F.col("n")).cast("int").alias("block"))
    texts = docs.select("doc_id", "text").join(members.select("doc_id"), "doc_id", "left_semi")
    held = C.cut(sets(texts, k).select("doc_id", "content", "shingles").dropDuplicates(["doc_id", "content"]).drop("content"), "sets")
    dealt = held.join(members, "doc_id").withColumn("o", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    units = dealt.select("family", F.least("block", "o").alias("i"), F.greatest("block", "o").alias("j"), "block", F.col("doc_id").alias("rep"), "shingles")
    ranged = units.repartition(C.width(spark), "family", "i", "j").sortWithinPartitions("family", "i", "j")
    return C.map_rows(ranged, lambda: alike(similarity), "a long, b long", flush=True)


def alike_groups(docs: DataFrame, similarity: float = 0.8, block: int | None = None) -> DataFrame:
    """(doc_id, component_id) of every row: the smallest doc_id reachable over pairs whose shingle sets have this Jaccard similarity or more.

    The radius with its room only finds families of candidates; sets whose sizes
    rule the similarity out never meet.  All pairs of a
    family are then compared on their shingle sets, and only links that hold
    make groups.  Texts with equal sets are one node.
    """
    each = C.cut(sets(docs, WIDE["k"]).withColumn("n", (F.length("shingles") / 8).cast("long")).drop("shingles"), "prints")
    distinct = C.cut(each.groupBy("content", *(f"f{i}" for i in range(LANES))).agg(F.min("doc_id").alias("rep"), size_bin(F.first("n"), similarity).alias("size_bin")), "distinct")
    how = {n: x for n, x in WIDE.items() if n != "k"}
    with C.rows_per_batch(docs.sparkSession, 200):
        families = C.cut(C.components(near_links(distinct.where("rep is not null"), wide_radius(similarity, ROOM), **how)), "families")
        found = C.components(verified(docs, families, similarity, WIDE["k"], block or BLOCK))
    named = distinct.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("content", F.coalesce("component", "rep").alias("component_id"))
    return each.join(named, "content").select("doc_id", "component_id")


def dedup(docs: DataFrame, similarity: float = 0.8) -> DataFrame:
    """Keeps the row with the smallest doc_id of each group of near copies, whose links are verified."""
    own = C.free(docs, "_gone")
    groups = alike_groups(docs, similarity).where(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias(own))
    return docs.join(groups, docs["doc_id"] == groups[own], "left_anti")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_groups(C.documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("f0"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {"op1_simhash": op1_simhash}
ORACLES: dict[str, str] = {}
