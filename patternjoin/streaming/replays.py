"""Streaming operators over tables replayed as files, drained into batches on shared storage."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..graph import build as G
from ..query import patterns as P
from .views import PatternView, folder, windowed_counts


def replay(rows: DataFrame, by: str, files: int = 3) -> DataFrame:
    """A stream of the rows in the order of `by`, one file for each micro-batch.

    The source takes files by their time of writing, so they are written one after another: files of
    one job would come in any order, and a watermark would drop rows that are not late.
    """
    path, at = folder(rows.sparkSession, "replay"), F.unix_micros(by)
    lo, hi = rows.agg(F.min(at), F.max(at)).first()
    turn = F.coalesce(F.floor((at - (lo or 0)) * files / ((hi or 0) - (lo or 0) + 1)), F.lit(0))
    for n in range(files):
        rows.where(turn == n).coalesce(1).write.mode("append").parquet(path)
    return rows.sparkSession.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """What the stream put out: all batches, or the last one in complete mode. A repeated batch overwrites itself."""
    spark = stream.sparkSession
    path = folder(spark, "drained")

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/n={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.parquet(path)
    return (out.where(F.col("n") == out.agg(F.max("n")).first()[0]) if mode == "complete" else out).drop("n")


def _events(spark: SparkSession, d: str) -> DataFrame:
    """Watermarks need instants, so times without a zone are read in the session's; results turn them back."""
    return G.table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")


def _plain(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


def tumbling(spark, d):
    return _plain(drained(windowed_counts(replay(_events(spark, d), "ts")).withColumnRenamed("n", "events"), "complete"))


def sliding(spark, d):
    w = F.window("ts", "60 minutes", "30 minutes").alias("w")
    return _plain(drained(replay(_events(spark, d), "ts").withWatermark("ts", "2 hours").groupBy(w).agg(F.count("*").alias("events")).select(
        F.col("w.start").alias("start"), "events"), "complete"))


def session(spark, d, gap: str = "30 minutes"):
    stream = replay(_events(spark, d), "ts").withWatermark("ts", "2 hours")
    return _plain(drained(stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events")).select(
        "user_id", F.col("w.start").alias("start"), "events"), "complete"))


def dedup(spark, d):
    """Edges of a stream once each, as long as repeats come within the watermark."""
    stream = replay(_events(spark, d), "ts").select("ts", F.col("user_id").alias("src"), F.length("event_type").cast("long").alias("dst"))
    return drained(stream.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["src", "dst"]).select("src", "dst"))


def static_join(spark, d):
    fixed = G.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return drained(replay(_events(spark, d), "ts").join(fixed, "user_id").select("event_id", "c_nationkey"))


def stream_join(spark, d):
    """Clicks and the purchases of the same user within ten minutes; both sides forget what is too old to match."""
    clicks = replay(_events(spark, d).where("event_type = 'click'"), "ts").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("c")).withWatermark("t1", "10 days")
    buys = replay(_events(spark, d).where("event_type = 'purchase'"), "ts").select(F.col("user_id").alias("u"), "ts", F.col("event_id").alias("p")).withWatermark("ts", "10 days")
    return drained(clicks.join(buys, F.expr("user_id = u and ts > t1 and ts <= t1 + interval 10 minutes")).select("c", "p"))


def state(spark, d):
    """Events of each user, counted in keyed state."""
    def count(key, frames, held):
        n = (held.get[0] if held.exists else 0) + sum(len(f) for f in frames)
        held.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n]})

    running = replay(_events(spark, d), "ts").groupBy("user_id").applyInPandasWithState(
        count, "user_id long, events long", "n long", "update", GroupStateTimeout.NoTimeout)
    return drained(running, "update").groupBy("user_id").agg(F.max("events").alias("events"))


def late(spark, d):
    """Hourly counts when the first day's file comes last: its rows are behind the watermark and go.

    A batch drops rows by the watermark that the batch before it ran with, so two files come first.
    """
    e = _events(spark, d).where("ts < timestamp'2024-01-21'")
    path = folder(spark, "late")
    for days in ("2024-01-02' and ts < timestamp'2024-01-11", "2024-01-11", "2024-01-01' and ts < timestamp'2024-01-02"):
        e.where(f"ts >= timestamp'{days}'").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return drained(windowed_counts(stream).withColumnRenamed("n", "events"))


def restarted_view(spark, d):
    """The triangle view stopped half-way and resumed from its log by another instance."""
    e = G.handoff(spark, d).withColumn("half", F.pmod(F.xxhash64("src", "dst"), F.lit(2)))
    source, view = folder(spark, "halves"), PatternView(spark, P.clique(3))
    for half in (0, 1):
        e.where(F.col("half") == half).select("src", "dst").write.mode("append").parquet(source)
        resumed = PatternView(spark, P.clique(3))
        resumed.path = view.path
        resumed.run(spark.readStream.schema("src long, dst long").parquet(source))
    return view.count(spark)


REPLAYS = {
    "st_tumbling": (tumbling, "select date_trunc('hour', ts) as start, event_type, count(*) as events from events group by 1, 2"),
    "st_sliding": (sliding, "select start, count(*) as events from (select unnest([time_bucket(interval 30 minutes, ts), time_bucket(interval 30 minutes, ts) - interval 30 minutes]) as start from events) group by 1"),
    "st_session": (session, """select user_id, min(ts) as start, count(*) as events from (select user_id, ts, sum(case when before is null or ts > before + interval 30 minutes then 1 else 0 end)
 over (partition by user_id order by ts, event_id) as s from (select *, lag(ts) over (partition by user_id order by ts, event_id) as before from events)) group by user_id, s"""),
    "st_dedup": (dedup, "select distinct user_id as src, length(event_type) as dst from events"),
    "st_static_join": (static_join, "select event_id, c_nationkey from events join customer on c_custkey = user_id"),
    "st_stream_join": (stream_join, "select a.event_id as c, b.event_id as p from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 10 minutes"),
    "st_state": (state, "select user_id, count(*) as events from events group by 1"),
    "st_late": (late, None),
}
