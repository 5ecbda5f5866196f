"""Queries that iterate: breadth-first search, shortest paths, PageRank, components.

Each round is a written table on shared storage, so a lost executor repeats one round at most and
plans do not grow with the number of rounds. The driver sees counts only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.build import nodes, symmetric
from ..streaming.views import folder


def written(df: DataFrame, path: str) -> DataFrame:
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bfs(edges: DataFrame, start: DataFrame, most: int | None = None) -> DataFrame:
    """(node, dist): hops from the nearest of the start nodes; what cannot be reached has no row."""
    spark, path, hops = edges.sparkSession, folder(edges.sparkSession, "bfs"), 0
    frontier = written(start.select("node").distinct(), f"{path}/dist=0")
    while (most is None or hops < most) and not frontier.isEmpty():
        hops += 1
        seen = spark.read.schema("node long, dist int").parquet(path)
        step = frontier.join(edges, F.col("node") == F.col("src")).select(F.col("dst").alias("node")).distinct()
        frontier = written(step.join(seen, "node", "left_anti"), f"{path}/dist={hops}")
    return spark.read.schema("node long, dist int").parquet(path)


def shortest_paths(edges: DataFrame, start: DataFrame, within: int | None = None) -> DataFrame:
    """(node, dist) over edges (src, dst, w) of positive weight: only nodes that got nearer go on."""
    path, turn = folder(edges.sparkSession, "nearest"), 0
    best = written(start.select("node", F.lit(0).cast("long").alias("dist"), F.lit(True).alias("fresh")).distinct(), f"{path}/0")
    while not best.where("fresh").isEmpty():
        turn += 1
        reach = best.where("fresh").join(edges, F.col("node") == F.col("src")).select(F.col("dst").alias("node"), (F.col("dist") + F.col("w")).alias("near"))
        if within is not None:
            reach = reach.where(F.col("near") <= within)
        both = best.drop("fresh").join(reach.groupBy("node").agg(F.min("near").alias("near")), "node", "full")
        best = written(both.select("node", F.least("dist", "near").alias("dist"),
                                   F.coalesce(F.col("near") < F.col("dist"), F.col("dist").isNull()).alias("fresh")), f"{path}/{turn}")
    return best.select("node", "dist")


def pagerank(edges: DataFrame, rounds: int = 10, damping: float = 0.85) -> DataFrame:
    """(node, rank): ranks sum to one; nodes without arcs give theirs to all."""
    path = folder(edges.sparkSession, "rank")
    out = written(edges.groupBy("src").agg(F.count("*").alias("arcs")).withColumnRenamed("src", "node"), f"{path}/out")
    every = written(nodes(edges).join(out, "node", "left"), f"{path}/nodes")
    n = max(1, every.count())
    rank = every.select("node", "arcs", F.lit(1.0 / n).alias("rank"))
    for turn in range(rounds):
        idle = rank.where("arcs is null").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
        given = rank.where("arcs is not null").join(edges, F.col("node") == F.col("src")).groupBy("dst").agg(F.sum(F.col("rank") / F.col("arcs")).alias("got"))
        rank = written(every.join(given, F.col("node") == F.col("dst"), "left").select(
            "node", "arcs", (F.lit((1 - damping + damping * idle) / n) + damping * F.coalesce("got", F.lit(0.0))).alias("rank")), f"{path}/{turn}")
    return rank.select("node", "rank")


def components(edges: DataFrame) -> DataFrame:
    """(node, component): the smallest node of its connected component, by alternating star joins.

    A hub's list is never gathered: stars are a minimum for each node and a join back.
    """
    path, turn, before = folder(edges.sparkSession, "component"), 0, None
    every = written(nodes(edges), f"{path}/nodes")
    links = written(edges.where("src <> dst").select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct(), f"{path}/0")
    while True:
        mark = tuple(links.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("src", "dst"), F.lit(1 << 31)))).first())
        if mark == before:
            break
        before, turn = mark, turn + 1
        both = symmetric(links)
        low = both.groupBy("src").agg(F.least(F.min("dst"), F.first("src")).alias("m"))
        large = both.join(low, "src").where("dst > src").select(F.col("dst").alias("src"), F.col("m").alias("dst")).where("src <> dst").distinct()
        large = written(large, f"{path}/{turn}-large")
        low = large.groupBy("src").agg(F.min("dst").alias("m"))
        small = large.join(low, "src").where("dst <> m").select(F.col("dst").alias("src"), F.col("m").alias("dst")).unionByName(low.toDF("src", "dst"))
        links = written(small.distinct(), f"{path}/{turn}")
    return every.join(links.toDF("node", "m"), "node", "left").select("node", F.coalesce("m", "node").alias("component"))
