"""Edge lists in files: Parquet, CSV, adjacency text, and a partitioned Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from crowding.sources.store import scratch


def write_parquet(edges: DataFrame, path: str | None = None) -> str:
    """Edges partitioned by graph."""
    path = path or scratch(edges.sparkSession, "edges")
    edges.write.partitionBy("graph").parquet(path)
    return path


def read_parquet(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("u long, v long, graph string").parquet(path).select("graph", "u", "v")


def write_bucketed(edges: DataFrame, table: str, buckets: int = 64) -> None:
    """A table bucketed by u, for joins on u without a shuffle."""
    edges.write.bucketBy(buckets, "u").sortBy("u").mode("overwrite").saveAsTable(table)


def write_csv(edges: DataFrame, path: str | None = None) -> str:
    path = path or scratch(edges.sparkSession, "edges-csv")
    edges.select("u", "v").write.csv(path, header=False)
    return path


def read_csv(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    return spark.read.schema("u long, v long").csv(path, sep=sep)


def write_adjacency(edges: DataFrame, path: str | None = None) -> str:
    """A line a vertex: its id, a colon, and its neighbours in order, every edge on both ends' lines."""
    path = path or scratch(edges.sparkSession, "adjacency")
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    line = F.concat(F.col("u").cast("string"), F.lit(":"), F.concat_ws(" ", F.transform(F.sort_array(F.collect_list("v")), lambda x: x.cast("string"))))
    both.groupBy("u").agg(line.alias("value")).select("value").write.text(path)
    return path


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    lines = spark.read.text(path).select(F.split("value", ":").alias("p"))
    ends = lines.select(F.col("p")[0].cast("long").alias("u"), F.explode(F.split(F.col("p")[1], " ")).alias("w"))
    return ends.select("u", F.col("w").cast("long").alias("v")).filter("u < v").distinct()


class _File(InputPartition):
    def __init__(self, uri: str):
        self.uri = uri


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        from pyarrow import fs

        system, top = fs.FileSystem.from_uri(self.path if "://" in self.path else self.path.replace("file:", "file://", 1))
        found = system.get_file_info(fs.FileSelector(top, recursive=True))
        return [_File(f.path) for f in found if f.is_file and f.size and not f.base_name.startswith(("_", "."))]

    def read(self, part):
        from pyarrow import csv, fs
        import pyarrow as pa

        system, _ = fs.FileSystem.from_uri(self.path if "://" in self.path else self.path.replace("file:", "file://", 1))
        with system.open_input_stream(part.uri) as f:
            options = csv.ReadOptions(column_names=["u", "v"])
            kinds = csv.ConvertOptions(column_types={"u": pa.int64(), "v": pa.int64()})
            yield from csv.open_csv(f, read_options=options, convert_options=kinds)


class EdgeListSource(DataSource):
    """format("edgelist"): comma-separated pairs below a path, a partition a file, in Arrow batches."""

    @classmethod
    def name(cls):
        return "edgelist"

    def schema(self):
        return "u long, v long"

    def reader(self, schema):
        return _Reader(self.options["path"])
