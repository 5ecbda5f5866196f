"""Connected components by contraction: every round hooks each node to its smallest
neighbour, jumps pointers twice and relabels the edges; no link reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, forget


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): root is the smallest node reachable. Nodes without edges are absent.

    Loops and repeated edges are harmless, null ends are dropped, no edges give no rows.
    """
    e = cut(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v").distinct(), "cc-edges")
    labels = None
    while True:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        hook = both.groupBy("u").agg(F.least("u", F.min("v")).alias("p"))
        hook = cut(hook, "cc-hook")
        for _ in range(2):
            up = hook.select(F.col("u").alias("p"), F.col("p").alias("pp"))
            hook = hook.join(up, "p", "left").select("u", F.coalesce("pp", "p").alias("p"))
        hook = cut(hook, "cc-jump")
        if labels is None:
            new = hook.select(F.col("u").alias("node"), F.col("p").alias("root"))
        else:
            new = labels.join(hook, F.col("root") == F.col("u"), "left").select(
                "node", F.coalesce("p", "root").alias("root"))
        new = cut(new, "cc-labels")
        forget(labels)
        labels = new
        pu = hook.select("u", F.col("p").alias("pu"))
        pv = hook.select(F.col("u").alias("v"), F.col("p").alias("pv"))
        rest = (e.join(pu, "u").join(pv, "v").where("pu <> pv")
                .select(F.least("pu", "pv").alias("u"), F.greatest("pu", "pv").alias("v")).distinct())
        rest = cut(rest, "cc-edges")
        forget(e)
        forget(hook)
        e = rest
        if e.isEmpty():
            forget(e)
            return labels
