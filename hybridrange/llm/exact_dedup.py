"""Exact dedup by content sort.

Sampled splitters range-partition the normalised bytes, an external sort puts
equal texts next to each other, and neighbours are compared in full; the
smallest identifier stays.  Copies that meet in one slice of a map task are
folded before the shuffle, so a hot group arrives as few rows.  Members find
their group again through the digest of the normalised text.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

GROUPS = "text_sha256 binary, keep_id long, keep_rid long, group_size long"


def normalise(text: bytes) -> bytes:
    """Each run of white space becomes one space, at both ends too."""
    if not text:
        return text
    body = b" ".join(text.split())
    if not body:
        return b" "
    return b" " * (text[:1] in C.WHITE and text[:1] != b"") + body + b" " * (text[-1:] in C.WHITE)


def smaller(x: list, doc_id: int | None, rid: int) -> None:
    """Puts the smaller of two (doc_id, rid) in x; a null doc_id is the largest."""
    if (doc_id is None, doc_id or 0, rid) < (x[0] is None, x[0] or 0, x[1]):
        x[:2] = doc_id, rid


def fold():
    """Equal texts of a slice become one row with their smallest id and their number."""

    def each(batch: pa.RecordBatch) -> dict:
        found: dict[bytes, list] = {}
        for doc_id, rid, text in zip(batch["doc_id"].to_pylist(), batch["rid"].to_pylist(), batch["text"].to_pylist(), strict=True):
            x = found.setdefault(normalise(text), [doc_id, rid, 0])
            smaller(x, doc_id, rid)
            x[2] += 1
        return {"text": list(found), "doc_id": [x[0] for x in found.values()], "rid": [x[1] for x in found.values()], "n": [x[2] for x in found.values()]}

    return each


def neighbours():
    """Compares each text of a sorted partition with the one before; emits a group when the next differs."""
    held: list = []

    def each(batch: pa.RecordBatch | None) -> dict | None:
        out = []
        if batch is None:
            out, held[:] = held[:], []
        else:
            for text, doc_id, rid, n in zip(*(batch[c].to_pylist() for c in ("text", "doc_id", "rid", "n")), strict=True):
                if held and held[0][3] == text:
                    smaller(held[0], doc_id, rid)
                    held[0][2] += n
                else:
                    out += held
                    held[:] = [[doc_id, rid, n, text]]
        return {"text_sha256": [hashlib.sha256(x[3]).digest() for x in out], "keep_id": [x[0] for x in out], "keep_rid": [x[1] for x in out], "group_size": [x[2] for x in out]} if out else None

    return each


def digests():
    def each(batch: pa.RecordBatch) -> dict:
        return {"doc_id": batch["doc_id"], "rid": batch["rid"], "text_sha256": [hashlib.sha256(normalise(x)).digest() for x in batch["text"].to_pylist()]}

    return each


def numbered(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.monotonically_increasing_id().alias("rid"), C.text_bytes().alias("text"))


def group_texts(docs: DataFrame) -> DataFrame:
    """One row for each distinct normalised text: its SHA-256, its smallest doc_id (and that row's number), its rows."""
    rows = C.map_rows(numbered(docs), fold, "text binary, doc_id long, rid long, n long")
    # the splitters need the beginning only, and a hash where many texts begin alike: the driver never samples whole texts
    ranged = rows.repartitionByRange(C.width(docs.sparkSession), F.substring("text", 1, 48), F.xxhash64("text")).sortWithinPartitions("text", "doc_id")
    return C.map_rows(ranged, neighbours, GROUPS, flush=True)


def members(docs: DataFrame) -> DataFrame:
    """Each row's doc_id, rid (its number in the scan), keep_id, group_size, kept and text_sha256 (hexadecimal).

    Null texts count as empty.  Of rows that repeat a doc_id with equal texts the
    first in the scan stays; a null doc_id stays only without another; an empty
    table gives no rows; other columns are ignored.
    """
    docs = C.stable(docs)
    each = C.cut(C.map_rows(numbered(docs), digests, "doc_id long, rid long, text_sha256 binary"), "digests")
    groups = C.cut(group_texts(docs), "groups").withColumn("times", F.col("group_size"))
    found = C.join_on_key(each, groups, ["text_sha256"], "times", each.count())
    return found.select("doc_id", "rid", "keep_id", "group_size", (F.col("rid") == F.col("keep_rid")).alias("kept"), F.lower(F.hex("text_sha256")).alias("text_sha256"))


def dedup(docs: DataFrame) -> DataFrame:
    """The rows that stay, with their columns as they are."""
    docs = C.stable(docs)
    rid = C.free(docs, "_rid")
    kept = group_texts(docs).select(F.col("keep_rid").alias(rid))  # one row a group, so nothing is hot
    return docs.withColumn(rid, F.monotonically_increasing_id()).join(kept, rid, "left_semi").select(*docs.columns)


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return members(C.documents(spark, sf_dir)).drop("rid")


SQL = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS x FROM documents),
g AS (SELECT x, min(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY x)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(x) AS text_sha256 FROM t JOIN g USING (x)
"""
QUERIES = {"op9_exact_dedup": op9_exact_dedup}
ORACLES = {"op9_exact_dedup": SQL}
