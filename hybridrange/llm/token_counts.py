"""Token counts as delta-maintained rollups.

A change is an insert, a delete or a revised count of one document under one
tokenizer version.  Each batch of changes is folded to signed sums by source,
language and version and committed under its own id: the folder of a batch is
overwritten when a broken commit is tried again, and its marker, written last,
makes every later try a no-op.  Totals are sums over the committed batches, and
``compact`` folds those into one batch without changing them.
"""

from __future__ import annotations

import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

#: Patterns whose matches are the tokens of a version.
VERSIONS = {"words-1": r"[^\x20\x09-\x0D]+", "wordpunct-1": r"[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]"}
KEYS = ["source", "lang", "tokenizer_version"]
DELTA = "source string, lang string, tokenizer_version string, docs long, tokens long"


def counted(text: Column, version: str) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(VERSIONS[version])), F.lit(0)).cast("long")


def bpe_counts(docs: DataFrame, ranks_file: str, version: str) -> DataFrame:
    """(doc_id, source, lang, tokenizer_version, tokens) with a public byte-level BPE, given as a file of ranks."""

    def make():
        import base64

        import public_tokenizers as P
        import tiktoken

        with open(ranks_file, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        coder = tiktoken.Encoding(version, pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})

        def each(batch: pa.RecordBatch) -> dict:
            n = [len(coder.encode_ordinary(x or "")) for x in batch["text"].to_pylist()]
            return {c: batch[c] for c in ("doc_id", "source", "lang")} | {"tokenizer_version": [version] * len(n), "tokens": n}

        return each

    return C.map_rows(docs.select("doc_id", "source", "lang", "text"), make, "doc_id long, source string, lang string, tokenizer_version string, tokens long")


def signed(changes: DataFrame) -> DataFrame:
    """Changes (kind, source, lang, tokenizer_version, tokens, old_tokens) folded to signed sums by group.

    An insert adds a document and its tokens, a delete takes them away, a revised
    count adds the difference.  Null sources and languages are groups of their
    own, null counts are 0, other kinds raise an error.
    """
    n, old = F.coalesce("tokens", F.lit(0)), F.coalesce("old_tokens", F.lit(0))
    known = F.when(F.col("kind").isin("insert", "delete", "revise"), F.col("kind")).otherwise(F.raise_error(F.lit("unknown kind of change")))
    rows = changes.select(*KEYS, F.when(known == "insert", 1).when(known == "delete", -1).otherwise(0).cast("long").alias("docs"), F.when(known == "insert", n).when(known == "delete", -n).otherwise(n - old).alias("tokens"))
    return rows.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").cast("long").alias("tokens"))


class Rollup:
    """The committed batches under one folder that driver and executors share."""

    def __init__(self, spark: SparkSession, place: str):
        self.spark, self.place = spark, place.rstrip("/")

    def path(self, name: str):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.place}/{name}")
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()), path

    def committed(self) -> list[str]:
        fs, path = self.path("markers")
        return sorted(x.getPath().getName() for x in fs.listStatus(path)) if fs.exists(path) else []

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Adds a batch once; False if it was committed before."""
        fs, marker = self.path(f"markers/{batch}")
        if fs.exists(marker):
            return False
        signed(changes).write.mode("overwrite").parquet(f"{self.place}/deltas/{batch}")
        fs.create(marker, True).close()
        return True

    def deltas(self) -> DataFrame:
        folders = [f"{self.place}/deltas/{x}" for x in self.committed()]
        return self.spark.read.schema(DELTA).parquet(*folders) if folders else self.spark.createDataFrame([], DELTA)

    def totals(self) -> DataFrame:
        """Documents and tokens of each group; groups without documents and tokens left are gone."""
        found = self.deltas().groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        return found.where("docs <> 0 or tokens <> 0")

    def compact(self, place: str) -> Rollup:
        """A rollup elsewhere that remembers all batch ids but has one folder of sums."""
        new = Rollup(self.spark, place)
        first, *rest = self.committed() or ["empty"]
        self.totals().write.mode("overwrite").parquet(f"{new.place}/deltas/{first}")
        for x in rest:
            self.spark.createDataFrame([], DELTA).write.mode("overwrite").parquet(f"{new.place}/deltas/{x}")
        for x in [first, *rest]:
            fs, marker = new.path(f"markers/{x}")
            fs.create(marker, True).close()
        return new


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loads every document at an estimate by its length, revises to exact counts, adds the second version, drops blank texts; each batch is sent twice."""
    docs = C.documents(spark, sf_dir)
    each = docs.select("source", "lang", F.floor(F.coalesce("n_chars", F.lit(0)) / 6).cast("long").alias("guess"), *[counted(F.col("text"), v).alias(v) for v in VERSIONS])
    each = C.cut(each, "counts")
    first, second = (F.col(f"`{v}`") for v in VERSIONS)
    none = F.lit(None).cast("long")
    change = lambda kind, version, n, old=none: each.select(F.lit(kind).alias("kind"), "source", "lang", F.lit(version).alias("tokenizer_version"), n.alias("tokens"), old.alias("old_tokens"), first.alias("words"))
    a, b = VERSIONS
    batches = {"load": change("insert", a, F.col("guess")), "revise": change("revise", a, first, F.col("guess")), "second": change("insert", b, second), "blank": change("delete", a, first).union(change("delete", b, second)).where("words = 0")}
    rollup = Rollup(spark, f"{C.shared_dir(spark)}/rollup-{uuid.uuid4().hex}")
    for name, changes in [*batches.items(), *batches.items()]:
        rollup.commit(name, changes)
    return rollup.totals()


SQL = r"""
WITH c AS (
  SELECT source, lang, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS a,
         len(regexp_extract_all(coalesce(text, ''), '[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]')) AS b
  FROM documents)
SELECT source, lang, v AS tokenizer_version, count(*) AS docs, CAST(sum(CASE WHEN v = 'words-1' THEN a ELSE b END) AS BIGINT) AS tokens
FROM c, (VALUES ('words-1'), ('wordpunct-1')) AS t(v) WHERE a > 0 GROUP BY source, lang, v
"""
QUERIES = {"op3_token_counts": op3_token_counts}
ORACLES = {"op3_token_counts": SQL}
