"""User-defined forms, SQL forms, recursion, graph forms and statistics: name -> (query, SQL that must agree)."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from ..graph import build as G
from ..graph.build import table as t
from ..operators import recursive as R
from ..query.model import parse_pattern
from ..streaming.replays import REPLAYS, restarted_view
from ..streaming.views import folder

_RET = "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey where a.l_returnflag = 'R' and b.l_returnflag = 'R'"
_DIR = "select distinct src, dst from (select user_id as src, lead(user_id) over (partition by cast(ts as date) order by ts, event_id) as dst from events) where dst is not null and src <> dst"
_PAGES = """with h as (select distinct page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as l from pages),
 k as (select l from h group by l having count(*) between 2 and 1000), m as (select * from h join k using (l)),
 e as (select distinct a.page_id as src, b.page_id as dst from m a join m b on a.l = b.l and a.page_id < b.page_id)"""
_DEG = f"with e as ({_RET}), g as (select node, count(*) as degree from (select src as node from e union all select dst from e) group by 1) "
_ROUNDS = 10


def _ranks_sql() -> str:
    out = [f"e as materialized ({_DIR})", "o as materialized (select src as node, count(*) as arcs from e group by 1)",
           "v as materialized (select node, arcs from (select src as node from e union select dst from e) left join o using (node))",
           "r0 as materialized (select node, arcs, 1.0 / (select count(*) from v)::double as rank from v)"]
    for i in range(_ROUNDS):
        out.append(f"""r{i + 1} as materialized (select v.node, v.arcs, (0.15 + 0.85 * (select coalesce(sum(rank), 0) from r{i} where arcs is null)) / (select count(*) from v)::double
 + 0.85 * coalesce(got, 0) as rank from v left join (select dst, sum(rank / arcs) as got from r{i} join e on node = src group by 1) on v.node = dst)""")
    return "with " + ", ".join(out) + f" select node, round(rank, 9) as rank from r{_ROUNDS}"


def _first(edges):
    return edges.agg(F.min("src").alias("node"))


def _weighted(spark, d):
    return G.handoff_dir(spark, d).withColumn("w", F.pmod(F.col("src") * 7 + F.col("dst") * 13, F.lit(10)) + 1)


def _arrow_udf(spark, d):
    @F.arrow_udf("boolean")
    def taken(node: pa.Array) -> pa.Array:
        rest = [(x * 2654435761 + 12345) % 4294967296 * 8 < 4294967296 for x in node.to_pylist()]
        return pa.array(rest, pa.bool_())

    return G.nodes(G.copurchase_ret(spark, d)).where(taken("node"))


def _pandas_udaf(spark, d):
    @F.pandas_udf("double")
    def sum_product(a: pd.Series, b: pd.Series) -> float:
        return float((a * b).sum())

    return t(spark, d, "lineitem").groupBy("l_suppkey").agg(sum_product("l_quantity", "l_linenumber").alias("w"))


def _map_in_arrow(spark, d):
    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.subtract(b.column(1), b.column(0))], names=["src", "gap"])

    return G.copurchase_ret(spark, d).mapInArrow(run, "src long, gap long")


def _cogroup(spark, d):
    """Sizes of both sides of a key; a side's rows are reduced first, so no group is gathered whole."""
    a = t(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("k")).agg(F.count("*").alias("lines"))
    b = t(spark, d, "orders").groupBy(F.col("o_orderkey").alias("k")).agg(F.count("*").alias("orders"))

    def both(left: pa.Table, right: pa.Table) -> pa.Table:
        k = (left if left.num_rows else right)["k"][0].as_py()
        return pa.table({"k": pa.array([k], pa.int64()), "lines": pa.array([pc.sum(left["lines"]).as_py() or 0], pa.int64()),
                         "orders": pa.array([pc.sum(right["orders"]).as_py() or 0], pa.int64())})

    return a.groupBy("k").cogroup(b.groupBy("k")).applyInArrow(both, "k long, lines long, orders long")


def _udtf(spark, d):
    @F.udtf(returnType="relation string, variable string, place int")
    class PatternRows:
        def eval(self, text: str):
            for a in parse_pattern(text).atoms if text else ():
                for place, v in enumerate(a.vars):
                    yield a.rel, v, place

    spark.udtf.register("pattern_rows", PatternRows)
    t(spark, d, "orders").createOrReplaceTempView("udtf_orders")
    return spark.sql("""select o_orderkey, p.relation, p.variable, p.place from udtf_orders, lateral pattern_rows(
        concat('e(o', o_orderkey, ', c', o_custkey, ') & f(c', o_custkey, ', ', o_orderstatus, ')')) p""")


def _views(spark, d):
    G.handoff_dir(spark, d).createOrReplaceTempView("handoff_arcs")
    return spark.sql("with h as (select src, count(*) as arcs from handoff_arcs group by src) select arcs, count(*) as nodes from h group by arcs")


def _bucketed(spark, d):
    """Edges stored by bucket of src in order of dst; a join on src reads them without a shuffle."""
    name = "edges_" + folder(spark, "b").rsplit("-", 1)[1]
    G.copurchase_ret(spark, d).write.bucketBy(8, "src").sortBy("src", "dst").option("path", folder(spark, "bucketed")).saveAsTable(name)
    e = spark.table(name)
    return e.toDF("src", "a").join(e.toDF("src", "b"), "src").where("a < b").groupBy("src").agg(F.count("*").alias("wedges"))


def _types(spark, d):
    path = folder(spark, "types")
    t(spark, d, "embeddings").write.parquet(path)
    back = spark.read.schema("vec_id long, embedding array<float>, label int").parquet(path)
    return back.select("vec_id", "label", F.size("embedding").alias("n"), F.element_at("embedding", 1).cast("double").alias("x"))


def _range_gap(spark, d):
    """Points strictly inside an open interval of their key."""
    p = t(spark, d, "part").select("p_partkey", "p_size", F.pmod("p_partkey", F.lit(5)).alias("k"))
    gaps = t(spark, d, "region").select(F.col("r_regionkey").cast("long").alias("k"), (F.col("r_regionkey") * 5).alias("lo"), (F.col("r_regionkey") * 5 + 20).alias("hi"))
    return p.join(gaps, "k").where("p_size > lo and p_size < hi").select("p_partkey", "lo", "hi")


def _natural(spark, d):
    x = t(spark, d, "lineitem")
    parts = [x.select(*c).distinct() for c in (("l_orderkey", "l_partkey"), ("l_partkey", "l_suppkey"), ("l_orderkey", "l_suppkey"))]
    out = parts[0]
    for p in parts[1:]:
        out = out.join(p, [c for c in out.columns if c in p.columns])
    return out.select("l_orderkey", "l_partkey", "l_suppkey")


def _disconnected(spark, d):
    n = lambda name: t(spark, d, name).agg(F.count("*").alias("n"), F.lit(1).alias("k"))
    return n("orders").toDF("a", "k").join(n("part").toDF("b", "k"), "k").select((F.col("a") * F.col("b")).alias("cnt"))


def _induced(spark, d):
    v = G.samples(G.copurchase_ret(spark, d), 8)["v1"]
    e = G.copurchase_ret(spark, d)
    return e.join(v.toDF("src"), "src", "left_semi").join(v.toDF("dst"), "dst", "left_semi").select("src", "dst")


_EVERY = "n as (select src as node from e union select dst from e)"
EXTENSIONS = {
    **REPLAYS,
    "st_restart": (restarted_view, f"with a as ({_DIR}), e as (select distinct least(src, dst) as src, greatest(src, dst) as dst from a) select count(*) as cnt from e x join e y on x.dst = y.src join e z on z.src = x.src and z.dst = y.dst"),
    "rec_bfs": (lambda s, d: (lambda e: R.bfs(e, _first(e)))(G.handoff_dir(s, d)), f"with recursive e as ({_DIR}), r(node, dist) as (select min(src), 0 from e union select e.dst, r.dist + 1 from r join e on r.node = e.src where r.dist < 30) select node, cast(min(dist) as int) as dist from r group by 1"),
    "rec_shortest_path": (lambda s, d: (lambda e: R.shortest_paths(e, _first(e)))(_weighted(s, d)), f"with recursive e as (select src, dst, (src * 7 + dst * 13) % 10 + 1 as w from ({_DIR})), r(node, dist) as (select min(src), 0::bigint from e union select e.dst, r.dist + e.w from r join e on r.node = e.src where r.dist + e.w <= 60) select node, min(dist) as dist from r group by 1"),
    "rec_pagerank": (lambda s, d: R.pagerank(G.handoff_dir(s, d), _ROUNDS).select("node", F.round("rank", 9).alias("rank")), _ranks_sql()),
    "rec_components": (lambda s, d: R.components(G.page_stars(s, d)), _PAGES.replace("with ", "with recursive ", 1) + ", b as (select src, dst from e union select dst, src from e), r(node, root) as (select src, src from b union select b.dst, r.root from r join b on r.node = b.src) select node, min(root) as component from r group by 1"),
    "udf_scalar_arrow": (_arrow_udf, f"with e as ({_RET}), {_EVERY} select node from n where ((node * 2654435761 + 12345) % 4294967296) * 8 < 4294967296"),
    "udaf_pandas": (_pandas_udaf, "select l_suppkey, sum(l_quantity * l_linenumber) as w from lineitem group by 1"),
    "map_in_arrow": (_map_in_arrow, f"select src, dst - src as gap from ({_RET})"),
    "cogroup_arrow": (_cogroup, "select k, coalesce(a.n, 0) as lines, coalesce(b.n, 0) as orders from (select l_orderkey as k, count(*) as n from lineitem group by 1) a full join (select o_orderkey as k, count(*) as n from orders group by 1) b using (k)"),
    "sql_udtf": (_udtf, "select o_orderkey, unnest(['e', 'e', 'f', 'f']) as relation, unnest(['o' || o_orderkey, 'c' || o_custkey, 'c' || o_custkey, o_orderstatus]) as variable, unnest([0, 1, 0, 1]) as place from orders where o_orderkey is not null and o_custkey is not null and o_orderstatus is not null"),
    "sql_views_cte": (_views, f"with h as (select src, count(*) as arcs from ({_DIR}) group by 1) select arcs, count(*) as nodes from h group by 1"),
    "sink_sorted_bucketed": (_bucketed, f"with e as ({_RET}) select a.src, count(*) as wedges from e a join e b on a.src = b.src and a.dst < b.dst group by 1"),
    "sink_roundtrip_types": (_types, "select vec_id, label, cast(len(embedding) as int) as n, cast(embedding[1] as double) as x from embeddings"),
    "filter_hash_sample": (lambda s, d: G.sample(t(s, d, "orders").select(F.col("o_custkey").alias("node")).distinct(), 8, 12345), "select distinct o_custkey as node from orders where ((o_custkey * 2654435761 + 12345) % 4294967296) * 8 < 4294967296"),
    "filter_range_gap": (_range_gap, "select p_partkey, r_regionkey * 5 as lo, r_regionkey * 5 + 20 as hi from part join region on p_partkey % 5 = r_regionkey and p_size > r_regionkey * 5 and p_size < r_regionkey * 5 + 20"),
    "join_natural_multi": (_natural, "select l_orderkey, l_partkey, l_suppkey from (select distinct l_orderkey, l_partkey from lineitem) join (select distinct l_partkey, l_suppkey from lineitem) using (l_partkey) join (select distinct l_orderkey, l_suppkey from lineitem) using (l_orderkey, l_suppkey)"),
    "join_self_edge": (lambda s, d: (lambda e: e.toDF("a", "b").join(e.toDF("b", "c"), "b").groupBy("b").agg(F.count("*").alias("wedges")))(G.copurchase_ret(s, d)), f"with e as ({_RET}) select x.dst as b, count(*) as wedges from e x join e y on x.dst = y.src group by 1"),
    "join_disconnected": (_disconnected, "select (select count(*) from orders) * (select count(*) from part) as cnt"),
    "fn_conditional_null": (lambda s, d: t(s, d, "customer").join(t(s, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n")), "c_custkey", "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"), F.nullif("c_nationkey", F.lit(0)).alias("k")),
        "select c_custkey, coalesce(n, 0) as n, nullif(c_nationkey, 0) as k from customer left join (select o_custkey as c_custkey, count(*) as n from orders group by 1) using (c_custkey)"),
    "sort_within_partitions": (lambda s, d: G.copurchase_ret(s, d).repartition("src").sortWithinPartitions("src", "dst"), _RET),
    "stat_degree_hist": (lambda s, d: G.degrees(G.copurchase_ret(s, d)).groupBy("degree").agg(F.count("*").alias("nodes")), _DEG + "select degree, count(*) as nodes from g group by 1"),
    "stat_wedges": (lambda s, d: G.degrees(G.copurchase_ret(s, d)).agg(F.sum(F.expr("degree * (degree - 1) div 2")).cast("long").alias("wedges")), _DEG + "select cast(sum(degree * (degree - 1) // 2) as bigint) as wedges from g"),
    "graph_symmetrise": (lambda s, d: G.symmetric(G.copurchase_ret(s, d)), f"with e as ({_RET}) select src, dst from e union select dst, src from e"),
    "graph_orient_degree": (lambda s, d: G.by_degree(G.copurchase_ret(s, d)), _DEG + "select case when (p.degree, e.src) <= (q.degree, e.dst) then e.src else e.dst end as src, case when (p.degree, e.src) <= (q.degree, e.dst) then e.dst else e.src end as dst from e join g p on p.node = e.src join g q on q.node = e.dst"),
    "graph_induce": (_induced, f"with e as ({_RET}) select src, dst from e where ((src * 2654435761 + 12345) % 4294967296) * 8 < 4294967296 and ((dst * 2654435761 + 12345) % 4294967296) * 8 < 4294967296"),
}
