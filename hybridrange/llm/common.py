"""Shared helpers: byte-level words, Arrow mapping, written cuts, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space; ``bytes.split()`` splits on exactly these bytes.
WHITE = b" \t\n\r\x0b\x0c"
#: Rows handed to Python code at once, so that long texts stay within memory.
SLICE = 256


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def words(text: bytes) -> list[bytes]:
    """Runs of bytes other than space and 0x09-0x0D, with A-Z in lower case."""
    return text.lower().split()


def text_bytes(name: str = "text") -> Column:
    """UTF-8 bytes of a text; null counts as empty."""
    return F.coalesce(F.col(name), F.lit("")).cast("binary")


def width(spark: SparkSession) -> int:
    """Partitions for a shuffle, as the session sets them."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def map_rows(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], Iterator[dict] | None]], schema: str, flush: bool = False) -> DataFrame:
    """``mapInArrow`` over slices of SLICE rows.

    ``make()`` runs once in a task and returns a function from a record batch to
    a dict of columns (or None for no rows); with ``flush`` that function is
    called once more with None when the input ends.
    """
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    struct = schema if isinstance(schema, StructType) else df.sparkSession.createDataFrame([], schema).schema
    arrow = to_arrow_schema(struct)

    def run(batches):
        each = make()

        def built(columns):
            return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, arrow.field(n).type) for n, x in ((n, columns[n]) for n in arrow.names)], schema=arrow)

        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                if (out := each(batch.slice(at, SLICE))) is not None:
                    yield built(out)
        if flush and (out := each(None)) is not None:
            yield built(out)

    return df.mapInArrow(run, struct)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from the session.

    Only a local master may do without: driver and executors are then one
    process, and a temporary folder is shared by nature.
    """
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that driver and executors share")
        place = tempfile.mkdtemp(prefix="shared-")
        spark.conf.set("spark.checkpoint.dir", place)
    return place.rstrip("/")


def free(df: DataFrame, name: str) -> str:
    """A column name like ``name`` that ``df`` does not have."""
    taken = {x.lower() for x in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


#: A key with more than this part of all rows is joined by a broadcast: there are at most so many.
HOT_KEYS = 10_000


def join_on_key(rows: DataFrame, keyed: DataFrame, on: list[str], times: str, total: int) -> DataFrame:
    """``rows`` joined with ``keyed``, which says under ``times`` how many of the ``total`` rows its key has.

    Rows of common keys would land in one task; there can be only HOT_KEYS keys
    with more than a HOT_KEYS-th of the rows, so these are sent to the rows.
    """
    common = F.col(times) * HOT_KEYS > F.lit(total)
    hot, rest = keyed.where(common).drop(times), keyed.where(~common).drop(times)
    if total <= HOT_KEYS:
        return rows.join(keyed.drop(times), on)
    return rows.join(F.broadcast(hot), on).unionByName(rows.join(rest, on))


#: Whether Spark deletes a query's shuffles when it ends; else they stay until the driver is short of memory.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame, name: str = "cut", clear: bool = False) -> DataFrame:
    """Writes a table in the shared folder and reads it back, which ends its lineage; with ``clear`` its shuffles are deleted at once."""
    spark = df.sparkSession
    place, before = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}", spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true" if clear else before)
    try:
        df.write.parquet(place)
    finally:
        spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(place)


def stable(docs: DataFrame) -> DataFrame:
    """Rows whose number in the scan is the same whenever and with whichever columns they are read: files as they are, anything else cut first."""
    node = docs._jdf.queryExecution().analyzed()
    while node.nodeName() in ("Project", "Filter", "SubqueryAlias", "View"):
        node = node.children().head()
    return docs if node.nodeName().startswith(("LogicalRelation", "Relation")) else cut(docs, "rows")


@contextmanager
def rows_per_batch(spark: SparkSession, rows: int) -> Iterator[None]:
    """Fewer rows in an Arrow batch while large binary rows are worked on; what runs inside has to be eager."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def drop_cut(df: DataFrame) -> None:
    """Deletes a table of ``cut`` that nothing reads any more."""
    spark = df.sparkSession
    for one in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(one)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spanning stars of the links a-b: (node, smallest node reachable) of all but the smallest."""
    nodes, inv = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j, label = inv[: len(a)], inv[len(a) :], np.arange(len(nodes))
    while True:
        low = np.minimum(label[i], label[j])
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        label = label[label]
        if (label[i] == label[j]).all() and (label[label] == label).all():
            break
    rest = label != np.arange(len(nodes))
    return nodes[rest], nodes[label[rest]]


def components(links: DataFrame) -> DataFrame:
    """(node, component): the smallest node reachable, for every node in ``links(a long, b long)``.

    Alternates two star contractions until nothing moves: each node points all
    its larger neighbours at its smallest neighbour, then all its smaller ones.
    Links stay distributed, and each round is cut.  Parallel links, loops and an
    empty table are allowed.
    """

    def print_of(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    edges = cut(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    seen = print_of(edges)
    while seen[0]:
        both = edges.union(edges.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        new = cut(small, "links")
        drop_cut(edges)
        edges, before, seen = new, seen, print_of(new)
        if before == seen:
            break
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).union(edges.select("b", "b").distinct())
