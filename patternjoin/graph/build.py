"""Graphs over the given tables: edge relations (src, dst) with set semantics."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SALTS = {"v1": 12345, "v2": 987654321, "v3": 555555555, "v4": 777777777}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _pairs(rows: DataFrame, group: str, node: str, second: DataFrame | None = None) -> DataFrame:
    """Unordered pairs of different nodes of one group, once each; the groups are small by construction."""
    a = rows.select(F.col(group).alias("g"), F.col(node).alias("src")).distinct()
    b = (second if second is not None else rows).select(F.col(group).alias("g"), F.col(node).alias("dst")).distinct()
    return a.join(b, "g").where("src < dst").select(F.col("src").cast("long"), F.col("dst").cast("long")).distinct()


def copurchase_rows(spark, sf_dir) -> DataFrame:
    """The pairs of copurchase as orders give them: a pair of several orders, or of repeated lines, comes several times."""
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("g"), F.col("l_partkey").cast("long").alias("src"))
    return rows.join(rows.toDF("g", "dst"), "g").where("src < dst").select("src", "dst")


def copurchase(spark, sf_dir) -> DataFrame:
    return _pairs(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey")


def copurchase_ret(spark, sf_dir) -> DataFrame:
    return _pairs(table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'"), "l_orderkey", "l_partkey")


def cosupply(spark, sf_dir) -> DataFrame:
    return _pairs(table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey")


def cosupply_ret(spark, sf_dir) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    return _pairs(rows.where("l_shipdate >= timestamp'2000-01-01'"), "l_orderkey", "l_suppkey", rows)


def handoff_dir(spark, sf_dir) -> DataFrame:
    # one window for each day: no task holds more than a day of events
    day = Window.partitionBy(F.to_date("ts")).orderBy("ts", "event_id")
    e = table(spark, sf_dir, "events").select("ts", "event_id", F.col("user_id").alias("src"))
    return e.withColumn("dst", F.lead("src").over(day)).where("dst is not null and src <> dst").select("src", "dst").distinct()


def handoff(spark, sf_dir) -> DataFrame:
    return unordered(handoff_dir(spark, sf_dir))


def sup_part(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst")).distinct()


def _bought(spark, sf_dir, item: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("dst"))
    return table(spark, sf_dir, "lineitem").select("l_orderkey", F.col(item).alias("src")).join(orders, "l_orderkey").select(
        "src", "dst").distinct()


def part_cust(spark, sf_dir) -> DataFrame:
    return _bought(spark, sf_dir, "l_partkey")


def sup_cust(spark, sf_dir) -> DataFrame:
    return _bought(spark, sf_dir, "l_suppkey")


def cust_part(spark, sf_dir) -> DataFrame:
    return part_cust(spark, sf_dir).select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def doc_share(spark, sf_dir) -> DataFrame:
    """Documents that share a line of 20 characters or more, however many hold it."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select(
        "doc_id", F.trim("l").alias("l")).where("length(l) >= 20").distinct()
    return _pairs(lines, "l", "doc_id")


def doc_classes(spark, sf_dir) -> DataFrame:
    """(node, w, ls): doc_share with the w documents of the same shared lines ls as one class.

    Documents of a class all share a line, and what one of them links to all link to. A class is named by its
    smallest document, its lines by 128-bit digests; lines of one document alone link nothing.
    """
    lines = table(spark, sf_dir, "documents").where("doc_id is not null").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select(
        "doc_id", F.trim("l").alias("l")).where("length(l) >= 20").select("doc_id", F.unhex(F.md5("l")).alias("l")).distinct()
    common = lines.groupBy("l").agg(F.count("*").alias("n")).where("n > 1").select("l")
    held = lines.join(common, "l").groupBy("doc_id").agg(F.sort_array(F.collect_set("l")).alias("ls"))
    return held.groupBy("ls").agg(F.min("doc_id").cast("long").alias("node"), F.count("*").alias("w"))


def _hrefs(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "pages").select(
        "page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()


def page_share(spark, sf_dir) -> DataFrame:
    return _pairs(_hrefs(spark, sf_dir), "href", "page_id")


def page_stars(spark, sf_dir) -> DataFrame:
    """The components of page_share with one edge for each page of an href, from its smallest page."""
    links = _hrefs(spark, sf_dir)
    first = links.groupBy("href").agg(F.min("page_id").alias("src"))
    return links.join(first, "href").where("src < page_id").select("src", F.col("page_id").alias("dst")).distinct()


def page_link(spark, sf_dir) -> DataFrame:
    """Page to target, targets coded by a digest of their address."""
    return _hrefs(spark, sf_dir).select(F.col("page_id").alias("src"), F.xxhash64("href").alias("dst"))


def word_next(spark, sf_dir) -> DataFrame:
    """Consecutive lower-cased English words; words are coded by a 64-bit digest."""
    words = F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))
    w = table(spark, sf_dir, "documents").where("lang = 'en'").select(F.transform(words, lambda x: F.xxhash64(x)).alias("w")).where("size(w) > 1")
    return w.select(F.explode(F.arrays_zip(F.slice("w", F.lit(1), F.size("w") - 1).alias("src"),
                                           F.slice("w", F.lit(2), F.size("w") - 1).alias("dst"))).alias("x")).select("x.src", "x.dst").distinct()


def vec_sim(spark, sf_dir, least: float = 0.3) -> DataFrame:
    """Pairs of vectors of one label cluster or not with cosine of at least `least` (small tables only)."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    v = v.withColumn("n", F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, x: a + x * x)))
    a, b = v.toDF("src", "x", "n"), v.toDF("dst", "y", "m")
    dot = F.aggregate(F.zip_with("x", "y", lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
    return a.join(b, F.col("src") < F.col("dst")).where(dot / (F.col("n") * F.col("m")) >= least).select("src", "dst")


GRAPHS = {f.__name__: f for f in (copurchase, copurchase_ret, cosupply, cosupply_ret, handoff_dir, handoff, sup_part, part_cust,
                                  sup_cust, cust_part, doc_share, page_share, page_link, word_next, vec_sim)}

# ---------------------------------------------------------------- forms of a graph


def unordered(edges: DataFrame) -> DataFrame:
    return edges.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def symmetric(edges: DataFrame) -> DataFrame:
    return edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    """(node, degree) of an unordered graph."""
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count("*").alias("degree"))


def by_degree(edges: DataFrame) -> DataFrame:
    """Each unordered pair from its end of lower degree (ties: smaller id): no hub keeps many arcs."""
    d = degrees(edges)
    e = edges.join(d.toDF("src", "ds"), "src").join(d.toDF("dst", "dd"), "dst")
    up = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("dst"))


def adjacency(edges: DataFrame, key: str = "src", other: str = "dst") -> DataFrame:
    """(node, nbrs): the sorted list of a node's partners."""
    return edges.groupBy(F.col(key).alias("node")).agg(F.array_sort(F.collect_set(other)).alias("nbrs"))


def nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def sample(node_set: DataFrame, s: int, salt: int) -> DataFrame:
    """Keeps a node with probability 1 / s, by integer arithmetic that any engine repeats."""
    return node_set.where(F.expr(f"pmod(node * 2654435761 + {salt}, 4294967296) * {s} < 4294967296"))


def samples(edges: DataFrame, s: int) -> dict[str, DataFrame]:
    every = nodes(edges)
    return {name: sample(every, s, salt) for name, salt in SALTS.items()}


def first_nodes(edges: DataFrame, n: int, salt: int) -> DataFrame:
    """The n nodes of lowest hash rank: samples that grow by containment."""
    return nodes(edges).orderBy(F.expr(f"pmod(node * 2654435761 + {salt}, 4294967296)"), "node").limit(n)


def first_edges(edges: DataFrame, n: int, salt: int = 12345) -> DataFrame:
    return edges.orderBy(F.expr(f"pmod((src * 31 + dst) * 2654435761 + {salt}, 4294967296)"), "src", "dst").limit(n)
