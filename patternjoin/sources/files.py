"""Readers and sinks: edge lists as text and as a data source, other formats, partitioned output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..graph.build import copurchase_ret, table
from ..streaming.views import folder

SPLIT = r"[\t ]+"


def write_edgelist(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.text(path)


def read_edgelist(spark: SparkSession, path: str) -> DataFrame:
    """Tab- or space-separated pairs of ids; lines that start with # are comments, blank and broken lines go."""
    parts = F.split(F.trim("value"), SPLIT)
    return (spark.read.text(path).where("trim(value) <> '' and not ltrim(value) like '#%'")
            .select(parts.getItem(0).try_cast("long").alias("src"), F.get(parts, F.lit(1)).try_cast("long").alias("dst")).dropna())


class _Part(InputPartition):
    def __init__(self, path: str, lo: int, hi: int):
        self.path, self.lo, self.hi = path, lo, hi


class EdgeListReader(DataSourceReader):
    """Byte ranges of local or mounted files; a line belongs to the range it starts in."""

    def __init__(self, path: str, block: int):
        self.path, self.block = path.removeprefix("file:"), block

    def partitions(self):
        import os

        files = sorted(os.path.join(self.path, f) for f in os.listdir(self.path) if not f.startswith(("_", "."))) if os.path.isdir(self.path) else [self.path]
        return [_Part(f, lo, min(lo + self.block, size)) for f in files if (size := os.path.getsize(f)) for lo in range(0, size, self.block)]

    def read(self, partition):
        with open(partition.path, "rb") as f:
            if partition.lo:
                f.seek(partition.lo - 1)
                f.readline()
            while f.tell() < partition.hi and (line := f.readline()):
                parts = line.split()
                if len(parts) >= 2 and not line.lstrip().startswith(b"#"):
                    yield int(parts[0]), int(parts[1])


class EdgeListSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> EdgeListReader:
        return EdgeListReader(self.options["path"], int(self.options.get("block", 1 << 25)))


def edgelist_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    path = folder(spark, "edges")
    write_edgelist(copurchase_ret(spark, d), path)
    return read_edgelist(spark, path)


def edgelist_source_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    path = folder(spark, "edges")
    write_edgelist(copurchase_ret(spark, d), path)
    spark.dataSource.register(EdgeListSource)
    return spark.read.format("edgelist").option("block", "65536").load(path)


def roundtrip(df: DataFrame, kind: str) -> DataFrame:
    """Written and read again with the schema declared, not inferred."""
    path = folder(df.sparkSession, kind)
    getattr(df.write.option("header", True) if kind == "csv" else df.write, kind)(path)
    reader = df.sparkSession.read.schema(df.schema)
    return getattr(reader.option("header", True) if kind == "csv" else reader, kind)(path)


def by_day(spark: SparkSession, d: str) -> DataFrame:
    """Events laid out by day; reading one day prunes the other folders."""
    path = folder(spark, "days")
    table(spark, d, "events").withColumn("day", F.to_date("ts")).write.partitionBy("day").parquet(path)
    return spark.read.parquet(path).where("day = date'2024-01-05'").select("event_id", "user_id")
