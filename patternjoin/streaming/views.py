"""Pattern views kept up to date as edges arrive, with Structured Streaming."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import build as G
from ..operators.acyclic import delta_count
from ..query import patterns as P
from ..query.model import JoinQuery


def folder(spark: SparkSession, label: str) -> str:
    """A fresh folder below the cluster's shared one; only a session of one machine may do without."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="patternjoin-")
    return f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"


class PatternView:
    """The edges seen so far and one delta of the count for each batch, both on shared storage.

    A batch writes its own folders and overwrites them when it is repeated, so a restart after a
    lost executor or driver counts nothing twice.
    """

    def __init__(self, spark: SparkSession, q: JoinQuery):
        self.q, self.path = q, folder(spark, "view")

    def edges(self, spark: SparkSession, before: int | None = None) -> DataFrame:
        all_ = spark.read.schema("src long, dst long, batch long").parquet(f"{self.path}/edges")
        return (all_ if before is None else all_.where(F.col("batch") < before)).select("src", "dst")

    def apply(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = batch.select("src", "dst").where("src is not null and dst is not null").distinct()
        try:
            base = self.edges(spark, number)
            base.schema
            base.isEmpty()
        except Exception as e:  # the first batch finds no folder yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            base = spark.createDataFrame([], "src long, dst long")
        delta_count(self.q, base, new).write.mode("overwrite").parquet(f"{self.path}/counts/n={number}")
        new.join(base, ["src", "dst"], "left_anti").withColumn("batch", F.lit(number).cast("long")).coalesce(8).write.mode(
            "overwrite").parquet(f"{self.path}/edges/n={number}")

    def count(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/counts").agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("cnt"))

    def run(self, stream: DataFrame) -> None:
        """Drain what the stream offers now."""
        query = (stream.writeStream.foreachBatch(self.apply).option("checkpointLocation", f"{self.path}/checkpoint")
                 .trigger(availableNow=True).start())
        query.awaitTermination()


def replayed_triangles(spark: SparkSession, sf_dir: str, batches: int = 3) -> DataFrame:
    """The triangle view of the handoff graph after its edges arrived in batches: equals a recount."""
    e = G.handoff(spark, sf_dir).withColumn("b", F.pmod(F.xxhash64("src", "dst"), F.lit(batches)))
    source = folder(spark, "arrivals")
    e.repartition(batches, "b").write.partitionBy("b").parquet(source)
    view = PatternView(spark, P.clique(3))
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(f"{source}/b=*")
    view.run(stream)
    return view.count(spark)


def windowed_counts(events: DataFrame, minutes: int = 60, late: str = "2 hours") -> DataFrame:
    """Events by type in tumbling windows; works on a stream (late rows are dropped) and on a table."""
    timed = events.withWatermark("ts", late) if events.isStreaming else events
    return timed.groupBy(F.window("ts", f"{minutes} minutes").alias("w"), "event_type").agg(F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), "event_type", "n")
