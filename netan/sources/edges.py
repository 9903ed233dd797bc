"""Edge lists in files: readers with fixed schemas, writers, a stream, and a Python source of generated networks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from netan.network import EDGE


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """(src, dst, weight). kind: parquet, orc, csv, json, or edgelist (ends parted by blanks, # and % start comments)."""
    if kind == "edgelist":
        return _parsed(spark, path).where("src IS NOT NULL AND dst IS NOT NULL").select("src", "dst", "weight")
    return spark.read.format(kind).options(**options).schema(EDGE).load(path)


def rejected(spark: SparkSession, path: str) -> DataFrame:
    """Lines of an edge list that are neither edges nor comments."""
    return _parsed(spark, path).where("src IS NULL OR dst IS NULL").select("line")


def _parsed(spark: SparkSession, path: str) -> DataFrame:
    lines = spark.read.text(path).select(F.trim("value").alias("line")).where("line <> '' AND NOT line RLIKE '^[#%]'")
    part = F.split("line", r"\s+")
    return lines.select("line", F.get(part, F.lit(0)).try_cast("long").alias("src"), F.get(part, F.lit(1)).try_cast("long").alias("dst"), F.coalesce(F.get(part, F.lit(2)).try_cast("double"), F.lit(1.0)).alias("weight"))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) from lines of a vertex and its neighbours."""
    parts = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("p")).where("p[0] <> ''")
    return parts.select(F.col("p")[0].try_cast("long").alias("src"), F.explode(F.slice("p", 2, 1 << 30)).alias("d")).select("src", F.col("d").try_cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")


def stream_edges(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EDGE).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def write_result(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    df.write.format(kind).mode(mode).partitionBy(*(partition_by or [])).save(path)


def save_table(df: DataFrame, name: str, buckets: int | None = None, by: str = "src", mode: str = "errorifexists") -> None:
    """A catalog table; with buckets, joins on `by` need no shuffle of it."""
    writer = df.write.mode(mode)
    (writer.bucketBy(buckets, by).sortBy(by) if buckets else writer).saveAsTable(name)


class RingSource(DataSource):
    """`spark.read.format("ring_lattice")`: n vertices, each tied to its next `reach` ones; split in ranges of vertices."""

    @classmethod
    def name(cls) -> str:
        return "ring_lattice"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return RingReader(int(self.options.get("n", 1000)), int(self.options.get("reach", 2)), int(self.options.get("parts", 4)))


class RingReader(DataSourceReader):
    def __init__(self, n: int, reach: int, parts: int) -> None:
        self.n, self.reach, self.parts = n, reach, parts

    def partitions(self):
        return [InputPartition((k * self.n // self.parts, (k + 1) * self.n // self.parts)) for k in range(self.parts)]

    def read(self, partition):
        a, b = partition.value
        for v in range(a, b):
            for d in range(1, self.reach + 1):
                yield v, (v + d) % self.n
