"""Document fingerprints by MinHash.

Universal multiply-add permutations over the hashes of five-word shingles give a
signature of minima in vectorised numpy; the share of equal places estimates the
Jaccard similarity.  Bands of the signature are joined in Spark and the pairs
that meet are verified on their shingle sets.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

SHINGLE = 5
PERMUTATIONS = 128
#: Word hashes that a task remembers.
MEMO = 300_000
_DRAW = np.random.default_rng(20240229)
_A = _DRAW.integers(0, 2**63, PERMUTATIONS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_B = _DRAW.integers(0, 2**63, PERMUTATIONS, dtype=np.uint64)
_POWERS = np.array([pow(0x9E3779B97F4A7C15, i, 2**64) for i in range(SHINGLE)], np.uint64)


class WordHashes(dict):
    """Word to XXH64, bounded."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= MEMO:
            self.clear()
        x = self[word] = xxhash.xxh64_intdigest(word)
        return x


def shingles(text: bytes, seen: dict) -> np.ndarray:
    """Hashes of the distinct five-word shingles; of the whole sequence if it is shorter, none without words."""
    w = C.words(text)
    if not w:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(seen.__getitem__, w), np.uint64, len(w))
    n = min(SHINGLE, len(h))
    with np.errstate(over="ignore"):
        x = np.zeros(len(h) - n + 1, np.uint64)
        for i in range(n):
            x += h[i : len(h) - n + 1 + i] * _POWERS[i]
        x ^= x >> np.uint64(29)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(32)
    return x


def signature(x: np.ndarray) -> np.ndarray:
    """PERMUTATIONS minima, 16 bits of each after a scramble, as the leading bits of minima vanish in long texts; all ones for no shingles."""
    least = np.full(PERMUTATIONS, 2**64 - 1, np.uint64)
    with np.errstate(over="ignore"):
        for at in range(0, len(x), 1024):
            moved = np.multiply.outer(_A, x[at : at + 1024])
            moved += _B[:, None]
            np.minimum(least, moved.min(1), out=least)
    if not len(x):
        return np.full(PERMUTATIONS, 2**16 - 1, np.uint16)
    with np.errstate(over="ignore"):
        least ^= least >> np.uint64(32)
        least *= np.uint64(0xD6E8FEB86659FD93)
        least ^= least >> np.uint64(32)
    return (least >> np.uint64(24)).astype(np.uint16)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    return float((a == b).mean())


def dealt(bounds: list[int], least: int):
    """Compressed texts with the range they belong to; the first of a range also closes the range before."""
    pack, cuts = zstandard.ZstdCompressor(level=1), np.array(bounds, np.int64)

    def each(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"bucket": [], "wrap": [], "key": [], "doc_id": [], "guard": [], "z": []}
        keys = batch["key"].to_pylist()
        for key, bucket, doc_id, text in zip(keys, np.searchsorted(cuts, keys, "right").tolist(), batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True):
            z = pack.compress(text)
            rows = [(bucket, 0, False)]
            if bucket and bounds[bucket - 1] == key:
                rows.append((bucket - 1, 0, True))
            if key == least:
                rows.append((len(bounds), 1, True))
            for b, wrap, guard in rows:
                for k, v in zip(out, (b, wrap, key, doc_id, guard, z), strict=True):
                    out[k].append(v)
        return out

    return each


def compared():
    """Each text of a sorted range against the one after it."""
    seen, unpack, held = WordHashes(), zstandard.ZstdDecompressor(), []

    def each(batch: pa.RecordBatch) -> dict | None:
        out: dict[str, list] = {"doc_id": [], "n_chars": [], "edited_sha256": [], "signature": [], "edited": [], "near_edited": [], "near_next": []}
        for bucket, doc_id, guard, z in zip(*(batch[c].to_pylist() for c in ("bucket", "doc_id", "guard", "z")), strict=True):
            raw = unpack.decompress(z)
            text, sig = raw.decode("utf-8", "surrogatepass"), signature(shingles(raw, seen))
            if held and held[0] == bucket and not held[2]:
                _, before, _, old, mine = held
                part = len(old) // 4
                new = (old[: len(old) - part] + text[:part]).encode("utf-8", "surrogatepass")
                other = signature(shingles(new, seen))
                for k, v in zip(out, (before, len(old), hashlib.sha256(new).hexdigest(), mine.tobytes(), other.tobytes(), likeness(mine, other), likeness(mine, sig)), strict=True):
                    out[k].append(v)
            held[:] = [bucket, doc_id, guard, text, sig]
        return out if out["doc_id"] else None

    return each


def against_next(docs: DataFrame) -> DataFrame:
    """Every row's signature beside those of its edited text and of the next document.

    Documents are dealt to ranges of doc_id, whose bounds are found on the ids
    alone, and sorted there; only the first text of a range travels twice.  The
    next of the last is the first, a single row follows itself.  Null texts count
    as empty, a null doc_id comes first, rows that repeat a doc_id follow each
    other in a fixed order, an empty table gives no rows.
    """
    spark = docs.sparkSession
    rows = docs.select("doc_id", F.coalesce("doc_id", F.lit(-(2**63))).alias("key"), C.text_bytes().alias("text"))
    n = C.width(spark)
    ids = rows.agg(F.min("key"), F.percentile_approx("key", [(i + 1) / n for i in range(max(1, n - 1))], 10_000)).first()
    least, bounds = ids[0], sorted(set(ids[1] or ()) - {ids[0]})
    spread = C.map_rows(rows, lambda: dealt(bounds, least), "bucket int, wrap int, key long, doc_id long, guard boolean, z binary")
    ranged = spread.repartitionById(len(bounds) + 1, F.col("bucket")).sortWithinPartitions("bucket", "wrap", "key", "z")
    return C.map_rows(ranged.select("bucket", "doc_id", "guard", "z"), compared, "doc_id long, n_chars long, edited_sha256 string, signature binary, edited binary, near_edited double, near_next double")


def signatures(docs: DataFrame) -> DataFrame:
    """(doc_id, signature, content) of every row; ``content`` names the text's words."""

    def make():
        seen = WordHashes()

        def each(batch: pa.RecordBatch) -> dict:
            texts = batch["text"].to_pylist()
            return {"doc_id": batch["doc_id"], "signature": [signature(shingles(x, seen)).tobytes() for x in texts], "content": [hashlib.sha256(b" ".join(C.words(x))).digest() for x in texts]}

        return each

    return C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), make, "doc_id long, signature binary, content binary")


def near_pairs(docs: DataFrame, similarity: float = 0.8, rows: int = 4) -> DataFrame:
    """(a, b, jaccard): pairs of class representatives whose five-word shingles are ``similarity`` alike.

    A class is the texts of equal words, named by its smallest doc_id; texts
    without words have none.  Classes that agree in a band of ``rows`` places
    meet by an equality join, and each pair is verified on the shingle sets.
    """
    every = C.cut(signatures(docs), "signatures").where(F.col("signature") != F.lit(b"\xff" * 2 * PERMUTATIONS))
    classes = every.groupBy("content", "signature").agg(F.min("doc_id").alias("rep"))
    bands = classes.select("rep", F.posexplode(F.array(*[F.substring("signature", 1 + 2 * rows * i, 2 * rows) for i in range(PERMUTATIONS // rows)])).alias("band", "part"))
    other = bands.withColumnRenamed("rep", "b")
    pairs = bands.withColumnRenamed("rep", "a").join(other, ["band", "part"]).where("a < b").select("a", "b").distinct()

    @F.pandas_udf("array<long>")
    def sets(text):
        seen = WordHashes()
        return text.map(lambda x: np.unique(shingles(x, seen)).view(np.int64))

    held = docs.join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").select("doc_id", sets(C.text_bytes()).alias("s"))
    both = pairs.join(held.select(F.col("doc_id").alias("a"), F.col("s").alias("x")), "a").join(held.select(F.col("doc_id").alias("b"), F.col("s").alias("y")), "b")
    shared = F.size(F.array_intersect("x", "y"))
    return both.select("a", "b", (shared / (F.size("x") + F.size("y") - shared)).alias("jaccard")).where(F.col("jaccard") >= similarity)


def op10_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    hexed = lambda c: F.lower(F.hex(c))
    found = against_next(C.documents(spark, sf_dir))
    return found.select("doc_id", "n_chars", "edited_sha256", hexed("signature").alias("fingerprint"), hexed("edited").alias("edited_fingerprint"), "near_edited", "near_next")


QUERIES = {"op10_minhash": op10_minhash}
ORACLES: dict[str, str] = {}
