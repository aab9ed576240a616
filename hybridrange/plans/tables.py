"""Reading the given tables, and cutting a plan at a written table."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from the session; only a local master may do without."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that driver and executors share")
        place = tempfile.mkdtemp(prefix="shared-")
        spark.conf.set("spark.checkpoint.dir", place)
    return place.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Writes a table in the shared folder and reads it back, which ends its lineage."""
    place = fresh_path(df.sparkSession, name)
    df.write.parquet(place)
    return df.sparkSession.read.schema(df.schema).parquet(place)


def width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Bytes up to which a side is sent to every executor.
BROADCAST_BYTES = 64 << 20


def small(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Hints a broadcast where rows times their bytes, arrays and texts by their greatest length, fit the limit; else leaves the choice to the optimizer."""
    wide = [f.name for f in df.schema.fields if f.dataType.typeName() == "array"]
    texts = [f.name for f in df.schema.fields if f.dataType.typeName() in ("string", "binary")]
    sizes = [F.coalesce(F.max(F.size(c)), F.lit(0)) * 8 for c in wide] + [F.coalesce(F.max(F.length(c)), F.lit(0)) * 4 for c in texts]
    n, *each = df.agg(F.count("*"), *sizes).first()
    return F.broadcast(df) if n * (16 * len(df.columns) + sum(each)) <= limit else df
