"""Line dedup by winnowing over line hashes.

The minimum of every window of RUN line hashes is a fingerprint, so any run of
RUN lines that occurs twice shares one at the same place.  Fingerprints that
occur once are dropped, the others carry the line hashes around them, by which
a match is extended both ways to every run through the fingerprint; of equal
runs the first in order of doc_id and line stays and the lines of the later
ones go.  Shorter runs count too once they reach WORDS words, one long line
included; these are found by a hash of their content.  The query leaves them
out, as its SQL knows runs of RUN lines only.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

#: Shortest repeated run of non-blank lines that is removed whatever its words.
RUN = 3
#: Words at which a repeated run of fewer lines is removed.
WORDS = 50


def line_hashes(text: bytes) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """All lines; the places of those that aren't blank, and the hashes of these without outer white space."""
    lines = text.split(b"\n")
    bare = [x.strip(C.WHITE) for x in lines]
    at = np.array([i for i, x in enumerate(bare) if x], np.int64)
    return lines, at, np.array([xxhash.xxh64_intdigest(bare[i]) for i in at], np.uint64)


def minima(h: np.ndarray, w: int) -> np.ndarray:
    """Places of the last minimum of every window of w hashes."""
    if len(h) < w:
        return np.empty(0, np.int64)
    views = np.lib.stride_tricks.sliding_window_view(h, w)[:, ::-1]
    return np.unique(np.arange(len(views)) + w - 1 - views.argmin(1))


def fingerprints(run: int):
    def each(batch: pa.RecordBatch) -> dict | None:
        doc, place, print_, first, around = [], [], [], [], []
        for doc_id, text in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True):
            _, _, h = line_hashes(text)
            for p in minima(h, run).tolist():
                low, high = max(0, p - run + 1), min(len(h), p + run)
                doc.append(doc_id)
                place.append(p)
                print_.append(h[p].astype(np.int64))
                first.append(low)
                around.append(h[low:high].view(np.int64).tolist())
        return {"doc_id": doc, "p": place, "print": print_, "first": first, "around": around} if doc else None

    return each


def wordy(run: int):
    """The runs of fewer than ``run`` non-blank lines that reach WORDS words."""

    def each(batch: pa.RecordBatch) -> dict | None:
        out: dict[str, list] = {"doc_id": [], "start": [], "n": [], "content": []}
        for doc_id, text in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), strict=True):
            bare = [x for x in (x.strip(C.WHITE) for x in text.split(b"\n")) if x]
            total = np.concatenate([[0], np.cumsum([len(x.split()) for x in bare])]) if bare else np.zeros(1, np.int64)
            for n in range(1, run):
                for s in np.flatnonzero(total[n:] - total[:-n] >= WORDS).tolist():
                    for k, v in zip(out, (doc_id, s, n, xxhash.xxh128_digest(b"\n".join(bare[s : s + n]))), strict=True):
                        out[k].append(v)
        return out if out["doc_id"] else None

    return each


def repeated_wordy(docs: DataFrame, run: int = RUN) -> DataFrame:
    """(doc_id, start, n): runs of n < ``run`` non-blank lines and WORDS words or more that occur before."""
    runs = C.cut(C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), lambda: wordy(run), "doc_id long, start long, n int, content binary"), "wordy")
    first = runs.groupBy("content").agg(F.min(F.struct("doc_id", "start")).alias("first"), F.count("*").alias("times")).where("times > 1")
    return runs.join(first, "content").where(F.struct("doc_id", "start") > F.col("first")).select("doc_id", "start", "n")


def repeated_starts(docs: DataFrame, run: int = RUN) -> DataFrame:
    """(doc_id, start): runs of ``run`` non-blank lines, by number in their text, that occur before."""
    rows = C.cut(C.map_rows(docs.select("doc_id", C.text_bytes().alias("text")), lambda: fingerprints(run), "doc_id long, p long, print long, first long, around array<long>"), "lines")
    again = rows.groupBy("print").count().where("count > 1").select("print")
    near = rows.join(again, "print")
    each = near.withColumn("i", F.explode(F.sequence(F.lit(0), F.size("around") - run)))
    # two hashes over the run keep chance collisions out
    part = F.slice("around", F.col("i") + 1, run)
    runs = each.select("doc_id", (F.col("first") + F.col("i")).alias("start"), F.xxhash64(part).alias("h1"), F.xxhash64(F.reverse(part), F.lit(1)).alias("h2")).distinct()
    runs = C.cut(runs, "runs")
    first = runs.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "start")).alias("first"), F.count("*").alias("n")).where("n > 1")
    return runs.join(first, ["h1", "h2"]).where(F.struct("doc_id", "start") > F.col("first")).select("doc_id", "start")


def kept_lines():
    def each(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"doc_id": [], "n_lines": [], "n_removed": [], "n_runs": [], "kept": []}
        for doc_id, text, starts in zip(batch["doc_id"].to_pylist(), batch["text"].to_pylist(), batch["starts"].to_pylist(), strict=True):
            lines, at, _ = line_hashes(text) if starts else (text.split(b"\n"), np.empty(0, np.int64), None)
            gone = np.zeros(len(at) + 1, bool)
            for x in starts or ():
                gone[x["start"] : x["start"] + x["n"]] = True
            lost = set(at[gone[:-1]].tolist())
            for k, v in (("doc_id", doc_id), ("n_lines", len(lines)), ("n_removed", len(lost)), ("n_runs", int((gone[1:] < gone[:-1]).sum())), ("kept", b"\n".join(x for i, x in enumerate(lines) if i not in lost))):
                out[k].append(v)
        return out

    return each


def dedup_lines(docs: DataFrame, run: int = RUN, short: bool = True) -> DataFrame:
    """(doc_id, n_lines, n_removed, n_runs, kept): every row with the text that stays.

    Lines end at line feeds and are compared without outer white space; blank
    lines always stay and don't break a run.  Null counts as empty (one blank
    line).  Rows that repeat a doc_id share their lines' places, so the runs of
    either count as occurring before only under a smaller place; texts shorter
    than a run lose only lines of WORDS words, and those only with ``short``; an
    empty table gives no rows.
    """
    found = repeated_starts(docs, run).withColumn("n", F.lit(run))
    if short:
        found = found.union(repeated_wordy(docs, run))
    starts = found.groupBy("doc_id").agg(F.collect_set(F.struct("start", "n")).alias("starts"))
    rows = docs.select("doc_id", C.text_bytes().alias("text")).join(starts, "doc_id", "left")
    return C.map_rows(rows, kept_lines, "doc_id long, n_lines long, n_removed long, n_runs long, kept binary")


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = dedup_lines(C.documents(spark, sf_dir), short=False)
    return found.select("doc_id", "n_lines", "n_removed", "n_runs", F.sha2("kept", 256).alias("kept_sha256"))


SQL = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
                  generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents),
b AS (SELECT doc_id, i, regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g') AS x FROM l),
f AS (SELECT doc_id, i, x, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS r FROM b WHERE x <> ''),
w AS (SELECT doc_id, r, x || chr(10) || lead(x, 1) OVER o || chr(10) || lead(x, 2) OVER o AS k FROM f WINDOW o AS (PARTITION BY doc_id ORDER BY r)),
s AS (SELECT doc_id, r, row_number() OVER (PARTITION BY k ORDER BY doc_id, r) AS nth FROM w WHERE k IS NOT NULL),
g AS (SELECT DISTINCT doc_id, r + d AS r FROM s, (VALUES (0), (1), (2)) AS t(d) WHERE nth > 1),
n AS (SELECT doc_id, count(*) AS n_removed, sum(CASE WHEN e THEN 1 ELSE 0 END) AS n_runs FROM
      (SELECT doc_id, lag(r) OVER (PARTITION BY doc_id ORDER BY r) IS DISTINCT FROM r - 1 AS e FROM g) GROUP BY doc_id),
k AS (SELECT l.doc_id, count(*) AS n_lines, string_agg(l.line, chr(10) ORDER BY l.i) FILTER (WHERE g.r IS NULL) AS kept
      FROM l LEFT JOIN f ON f.doc_id = l.doc_id AND f.i = l.i LEFT JOIN g ON g.doc_id = f.doc_id AND g.r = f.r GROUP BY l.doc_id)
SELECT k.doc_id, n_lines, coalesce(n_removed, 0) AS n_removed, CAST(coalesce(n_runs, 0) AS BIGINT) AS n_runs, sha256(coalesce(kept, '')) AS kept_sha256
FROM k LEFT JOIN n ON n.doc_id = k.doc_id
"""
QUERIES = {"op8_line_dedup": op8_line_dedup}
ORACLES = {"op8_line_dedup": SQL}
