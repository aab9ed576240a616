"""A Python data source that reads one version of a stored index: ``spark.read.format("window_stack")``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from hybridrange.methods import built
from hybridrange.plans.tables import fresh_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


class Segment(InputPartition):
    """The rows of one segment, read by one task."""

    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class Reader(DataSourceReader):
    def __init__(self, options):
        self.root = options["path"]
        self.files = options["files"].split(";")

    def partitions(self):
        return [Segment(x) for x in self.files]

    def read(self, partition):
        """Opens its file through Arrow's own file systems, as the path says."""
        from pyarrow import fs
        from pyarrow import parquet as pq

        store, path = fs.FileSystem.from_uri(partition.path)
        for batch in pq.ParquetFile(store.open_input_file(path)).iter_batches(columns=["seg", "ord", "id", "links"]):
            for row in batch.to_pylist():
                yield row["seg"], row["ord"], row["id"], sum(len(x) for x in row["links"])


class WindowStackSource(DataSource):
    @classmethod
    def name(cls):
        return "window_stack"

    def schema(self):
        return "seg long, ord int, id long, n_links int"

    def reader(self, schema):
        return Reader(self.options)


def read_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(layers, rows): the index of the embeddings, written and read through the source."""
    path = fresh_path(spark, "index")
    built(spark, sf_dir).write.parquet(path)
    spark.dataSource.register(WindowStackSource)
    files = spark.read.parquet(path).inputFiles()
    rows = spark.read.format("window_stack").option("path", path).option("files", ";".join(files)).load()
    return rows.agg(F.count("*").alias("n"), F.min(F.col("n_links") >= 1).alias("linked"))


QUERIES["source_index_reader"] = read_index
ORACLES["source_index_reader"] = "SELECT count(*) AS n, true AS linked FROM embeddings"
