"""Relational operators around the pattern methods: name -> (query, SQL that must agree)."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..graph.build import table as t
from ..sources import files
from ..streaming.views import windowed_counts

_DAY = "cast(o_orderdate as date)"


def _adj(spark, d):
    from ..graph.build import adjacency, copurchase_ret

    return adjacency(copurchase_ret(spark, d))


_RET = "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey where a.l_returnflag = 'R' and b.l_returnflag = 'R'"
_ADJ = f"with e as ({_RET}), g as (select src as node, list_sort(list(dst)) as nbrs from e group by 1) "
_SETS = {"union": "union", "union_all": "union all", "intersect": "intersect", "intersect_all": "intersect all", "except": "except", "except_all": "except all"}


def _two(spark, d):
    a = t(spark, d, "lineitem").where("l_returnflag = 'R'").select("l_partkey", "l_suppkey")
    return a, t(spark, d, "lineitem").where("l_returnflag = 'A'").select("l_partkey", "l_suppkey")


def _set(name):
    def run(spark, d):
        a, b = _two(spark, d)
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b),
                "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[name]()

    flag = "select l_partkey, l_suppkey from lineitem where l_returnflag = '{}'"
    return run, f"{flag.format('R')} {_SETS[name]} {flag.format('A')}"


def _join(how):
    def run(spark, d):
        o = t(spark, d, "orders").where("o_totalprice > 300000").select("o_orderkey", F.col("o_custkey").alias("c_custkey"))
        return t(spark, d, "customer").where("c_nationkey < 5").select("c_custkey", "c_mktsegment").join(o, "c_custkey", how)

    kind = {"inner": "join", "left": "left join", "right": "right join", "full": "full join"}.get(how)
    c, o = "(select c_custkey, c_mktsegment from customer where c_nationkey < 5)", "(select o_orderkey, o_custkey as c_custkey from orders where o_totalprice > 300000)"
    if kind:
        return run, f"select c_custkey, c_mktsegment, o_orderkey from {c} {kind} {o} using (c_custkey)"
    return run, f"select * from {c} x where {'' if how == 'left_semi' else 'not '}exists (select 1 from {o} y where y.c_custkey = x.c_custkey)"


#: A relation of more rows than this is not broadcast, whatever the hint: driver and executors each hold it whole.
BROADCAST_ROWS = 500_000


def _hinted(hint):
    def run(spark, d):
        o = t(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderpriority")
        if hint != "broadcast" or o.count() <= BROADCAST_ROWS:
            o = o.hint(hint)
        return t(spark, d, "lineitem").select("l_orderkey", "l_quantity").join(o, "l_orderkey").groupBy("o_orderpriority").agg(
            F.count("*").alias("n"), F.sum("l_quantity").alias("q"))

    return run, "select o_orderpriority, count(*) as n, sum(l_quantity) as q from lineitem join orders on l_orderkey = o_orderkey group by 1"


def _asof(spark, d):
    e = t(spark, d, "events")
    last = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    return e.withColumn("click_id", F.last(click, ignorenulls=True).over(last)).where("event_type = 'purchase'").select("event_id", "click_id")


def _salted(spark, d, salts: int = 8):
    a = t(spark, d, "lineitem").select("l_suppkey", "l_quantity").withColumn("salt", F.pmod(F.xxhash64("l_quantity"), F.lit(salts)))
    b = t(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    return a.join(b, ["l_suppkey", "salt"]).groupBy("s_nationkey").agg(F.count("*").alias("n"))


def _binned(spark, d):
    e = t(spark, d, "events").select("event_id", "ts", F.date_trunc("hour", "ts").alias("bin"))
    gaps = e.select("bin").distinct().select("bin", (F.col("bin") + F.expr("interval 10 minutes")).alias("lo"), (F.col("bin") + F.expr("interval 40 minutes")).alias("hi"))
    return e.join(gaps, "bin").where("ts > lo and ts < hi").select("event_id", "lo")


def _star(spark, d):
    n = t(spark, d, "nation").join(t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return (t(spark, d, "lineitem").join(t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
            .join(t(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
            .groupBy("r_name").agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue")))


def _o():
    # columns need a running session, so the window is made when a query is
    return W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_OW = "over (partition by o_custkey order by o_orderdate, o_orderkey)"


def _lateral(spark, d):
    t(spark, d, "customer").createOrReplaceTempView("lat_customer")
    t(spark, d, "orders").createOrReplaceTempView("lat_orders")
    return spark.sql("select c_custkey, o_orderkey from lat_customer, lateral (select o_orderkey from lat_orders where o_custkey = c_custkey order by o_totalprice desc nulls last, o_orderkey nulls last limit 3)")


def _grouping(spark, d):
    t(spark, d, "customer").createOrReplaceTempView("gs_customer")
    return spark.sql("select c_nationkey, c_mktsegment, count(*) as n, cast(grouping_id(c_nationkey, c_mktsegment) as int) as g from gs_customer group by grouping sets ((c_nationkey), (c_mktsegment), ())")


def _arrays(spark, d):
    x = _adj(spark, d).toDF("node", "a").withColumn("b", F.slice("a", 2, 3))
    text = lambda c: F.array_join(F.transform(c, lambda v: v.cast("string")), ",")
    return x.select("node", text(F.array_intersect("a", "b")).alias("i"), F.size(F.array_union("a", "b")).alias("u"), text(F.array_except("a", "b")).alias("x"),
                    F.array_contains("a", F.lit(100)).alias("has"), F.element_at("a", 1).alias("first"))


def _higher(spark, d):
    return _adj(spark, d).select("node", F.array_join(F.transform(F.filter("nbrs", lambda x: x > F.col("node") + 100), lambda v: v.cast("string")), ",").alias("far"),
                                 F.aggregate("nbrs", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"),
                                 F.exists("nbrs", lambda x: x % 7 == 0).alias("seven"))


_L = "lineitem"
OPERATORS = {
    "scan_pruned": (lambda s, d: t(s, d, _L).select("l_orderkey", "l_partkey", "l_quantity"), "select l_orderkey, l_partkey, l_quantity from lineitem"),
    "scan_pushdown": (lambda s, d: t(s, d, _L).where("l_shipdate >= timestamp'1997-06-01'").select("l_orderkey", "l_shipdate"), "select l_orderkey, l_shipdate from lineitem where l_shipdate >= timestamp '1997-06-01'"),
    "scan_edgelist_text": (files.edgelist_roundtrip, _RET),
    "scan_edgelist_source": (files.edgelist_source_roundtrip, _RET),
    **{f"scan_{k}": (lambda s, d, k=k: files.roundtrip(t(s, d, "part").select("p_partkey", "p_name", "p_size"), k), "select p_partkey, p_name, p_size from part") for k in ("csv", "json", "orc", "parquet")},
    "sink_partitioned": (lambda s, d: files.by_day(s, d), "select event_id, user_id from events where cast(ts as date) = date '2024-01-05'"),
    "project_distinct": (lambda s, d: t(s, d, _L).select("l_partkey", "l_suppkey").distinct(), "select distinct l_partkey, l_suppkey from lineitem"),
    "project_rename": (lambda s, d: t(s, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("name")), "select p_partkey as id, p_name as name from part"),
    "filter_in_between_like_null_case": (lambda s, d: t(s, d, "part").where(F.col("p_size").between(5, 20) & F.col("p_size").isin(5, 7, 11, 13) & F.col("p_name").isNotNull() & ~F.col("p_brand").like("%zz%")).select("p_partkey", F.when(F.col("p_size") > 10, "big").otherwise("small").alias("c")),
        "select p_partkey, case when p_size > 10 then 'big' else 'small' end as c from part where p_size between 5 and 20 and p_size in (5, 7, 11, 13) and p_name is not null and p_brand not like '%zz%'"),
    **{f"join_{k}": _join(k) for k in ("inner", "left", "right", "full", "left_semi", "left_anti")},
    **{f"join_hint_{k}": _hinted(k) for k in ("shuffle_hash", "merge", "broadcast")},
    "join_nested_loop": (lambda s, d: t(s, d, "nation").join(t(s, d, "region").hint("shuffle_replicate_nl"), F.col("n_regionkey") >= F.col("r_regionkey")).select("n_name", "r_name"), "select n_name, r_name from nation join region on n_regionkey >= r_regionkey"),
    "join_theta": (lambda s, d: (lambda a: a.toDF("k1", "n", "b1").join(a.toDF("k2", "n", "b2"), "n").where("b1 < b2").select("k1", "k2"))(t(s, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")), "select a.s_suppkey as k1, b.s_suppkey as k2 from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_acctbal < b.s_acctbal"),
    "join_range_binned": (_binned, "select event_id, lo from (select event_id, ts, date_trunc('hour', ts) + interval 10 minutes as lo, date_trunc('hour', ts) + interval 40 minutes as hi from events) where ts > lo and ts < hi"),
    "join_interval_time": (lambda s, d: (lambda e: e.where("event_type = 'click'").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("c")).join(e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("p")), "user_id").where("ts > t1 and ts <= t1 + interval 10 minutes").select("c", "p"))(t(s, d, "events")), "select a.event_id as c, b.event_id as p from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 10 minutes"),
    "join_asof": (_asof, "select event_id, click_id from (select event_id, event_type, last_value(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as click_id from events) where event_type = 'purchase'"),
    "join_cross_small": (lambda s, d: t(s, d, "region").select(F.col("r_name").alias("a")).crossJoin(t(s, d, "region").select(F.col("r_name").alias("b"))), "select a.r_name as a, b.r_name as b from region a, region b"),
    "join_lateral": (_lateral, "select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 3)"),
    "join_skew_salted": (_salted, "select s_nationkey, count(*) as n from lineitem join supplier on l_suppkey = s_suppkey group by 1"),
    "join_star_olap": (_star, "select r_name, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1"),
    "agg_group": (lambda s, d: t(s, d, _L).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"), F.round(F.avg("l_discount"), 8).alias("a"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi")), "select l_returnflag, l_linestatus, count(*) as n, sum(l_quantity) as q, round(avg(l_discount), 8) as a, min(l_tax) as lo, max(l_tax) as hi from lineitem group by 1, 2"),
    "agg_count_distinct": (lambda s, d: t(s, d, _L).groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("n")), "select l_suppkey, count(distinct l_partkey) as n from lineitem group by 1"),
    "agg_approx_distinct": (lambda s, d: t(s, d, _L).agg(F.approx_count_distinct("l_partkey", 0.02).alias("n")), None),
    "agg_percentile_approx": (lambda s, d: t(s, d, _L).agg(F.percentile_approx("l_quantity", [0.25, 0.5, 0.75]).alias("q")), None),
    "agg_sum_product": (lambda s, d: t(s, d, _L).groupBy("l_suppkey").agg(F.sum(F.col("l_quantity") * F.col("l_linenumber")).alias("w")), "select l_suppkey, sum(l_quantity * l_linenumber) as w from lineitem group by 1"),
    "agg_rollup": (lambda s, d: t(s, d, "customer").rollup("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")), "select c_nationkey, c_mktsegment, count(*) as n from customer group by rollup (c_nationkey, c_mktsegment)"),
    "agg_cube": (lambda s, d: t(s, d, "customer").cube("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")), "select c_nationkey, c_mktsegment, count(*) as n from customer group by cube (c_nationkey, c_mktsegment)"),
    "agg_grouping_sets": (_grouping, "select c_nationkey, c_mktsegment, count(*) as n, cast(grouping_id(c_nationkey, c_mktsegment) as int) as g from customer group by grouping sets ((c_nationkey), (c_mktsegment), ())"),
    "agg_pivot": (lambda s, d: t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).select("o_orderpriority", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"]), "select o_orderpriority, count(*) filter (where o_orderstatus = 'F') as f, count(*) filter (where o_orderstatus = 'O') as o, count(*) filter (where o_orderstatus = 'P') as p from orders group by 1"),
    "agg_having": (lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), F.count_if(F.col("o_orderstatus") == "F").alias("f")).where("n > 10"), "select o_custkey, count(*) as n, count(*) filter (where o_orderstatus = 'F') as f from orders group by 1 having count(*) > 10"),
    "agg_collect_adjacency": (lambda s, d: _adj(s, d).select("node", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs")), _ADJ + "select node, array_to_string(nbrs, ',') as nbrs from g"),
    "agg_stddev": (lambda s, d: t(s, d, _L).groupBy("l_returnflag").agg(F.round(F.stddev("l_quantity"), 6).alias("s"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c")), "select l_returnflag, round(stddev_samp(l_quantity), 6) as s, round(corr(l_quantity, l_extendedprice), 6) as c from lineitem group by 1"),
    "agg_max_by": (lambda s, d: t(s, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("best")), "select c_nationkey, arg_max(c_custkey, row(c_acctbal, c_custkey)) as best from customer group by 1"),
    "win_ranks": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.row_number().over(_o()).alias("r"), F.rank().over(W.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("k"), F.dense_rank().over(W.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("dk")), f"select o_orderkey, row_number() {_OW} as r, rank() over (partition by o_custkey order by o_orderstatus) as k, dense_rank() over (partition by o_custkey order by o_orderstatus) as dk from orders"),
    "win_lag_lead": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(_o()).alias("before"), F.lead("o_orderkey").over(_o()).alias("after")), f"select o_orderkey, lag(o_orderkey) {_OW} as before, lead(o_orderkey) {_OW} as after from orders"),
    "win_ntile": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.ntile(4).over(_o()).alias("n")), f"select o_orderkey, ntile(4) {_OW} as n from orders"),
    "win_running": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(_o().rowsBetween(-2, 0)), 2).alias("s")), "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row), 2) as s from orders"),
    "win_first_last": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.first("o_orderkey").over(_o()).alias("f"), F.nth_value("o_orderkey", 2).over(_o()).alias("n2")), f"select o_orderkey, first_value(o_orderkey) {_OW} as f, nth_value(o_orderkey, 2) {_OW} as n2 from orders"),
    "sort_topk": (lambda s, d: t(s, d, "part").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10).select("p_partkey", "p_retailprice"), "select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 10"),
    "sort_topk_per_group": (lambda s, d: t(s, d, "part").withColumn("r", F.row_number().over(W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("r <= 3").select("p_brand", "p_partkey"), "select p_brand, p_partkey from part qualify row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) <= 3"),
    "limit_offset": (lambda s, d: t(s, d, "orders").orderBy("o_orderkey").offset(20).limit(15).select("o_orderkey"), "select o_orderkey from orders order by o_orderkey limit 15 offset 20"),
    **{f"set_{k}": _set(k) for k in _SETS},
    "fn_string": (lambda s, d: t(s, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.length(F.trim("p_type")).alias("n"), F.substring("p_name", 2, 3).alias("x"), F.concat_ws("-", "p_brand", "p_type").alias("c"), F.instr("p_name", "a").alias("i")), "select p_partkey, upper(p_name) as u, cast(length(trim(p_type)) as int) as n, substring(p_name, 2, 3) as x, concat_ws('-', p_brand, p_type) as c, cast(instr(p_name, 'a') as int) as i from part"),
    "fn_words": (lambda s, d: t(s, d, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("n")), "select doc_id, cast(len(regexp_extract_all(lower(text), '[a-z]+')) as int) as n from documents"),
    "fn_url": (lambda s, d: t(s, d, "pages").select("page_id", F.expr("parse_url(url, 'HOST')").alias("host")), "select page_id, regexp_extract(url, '://([^/]*)', 1) as host from pages"),
    "fn_date": (lambda s, d: t(s, d, "orders").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("n")), "select o_orderkey, strftime(o_orderdate, '%Y-%m-%d') as day, cast(datediff('day', date '1995-01-01', cast(o_orderdate as date)) as int) as n from orders"),
    "fn_math": (lambda s, d: t(s, d, "part").select("p_partkey", F.pmod("p_partkey", F.lit(7)).alias("m"), F.round(F.sqrt("p_retailprice"), 6).alias("r"), F.round(F.log2("p_retailprice"), 6).alias("l"), F.greatest("p_size", F.lit(10)).alias("g")), "select p_partkey, p_partkey % 7 as m, round(sqrt(p_retailprice), 6) as r, round(log2(p_retailprice), 6) as l, greatest(p_size, 10) as g from part"),
    "fn_array": (_arrays, _ADJ + ", h as (select node, nbrs as a, nbrs[2:4] as b from g) select node, array_to_string(list_filter(a, lambda x: list_contains(b, x)), ',') as i, cast(len(a) as int) as u, array_to_string(list_filter(a, lambda x: not list_contains(b, x)), ',') as x, list_contains(a, 100) as has, a[1] as first from h"),
    "fn_higher_order": (_higher, _ADJ + "select node, array_to_string(list_filter(nbrs, lambda x: x > node + 100), ',') as far, cast(list_sum(nbrs) as bigint) as total, len(list_filter(nbrs, lambda x: x % 7 = 0)) > 0 as seven from g"),
    "fn_explode": (lambda s, d: _adj(s, d).select("node", F.posexplode("nbrs").alias("p", "x")), _ADJ + "select node, cast(unnest(range(len(nbrs))) as int) as p, unnest(nbrs) as x from g"),
    "fn_map": (lambda s, d: t(s, d, "customer").groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_custkey", "c_acctbal"))).alias("m")).select("c_nationkey", F.size(F.map_keys("m")).alias("n")), "select c_nationkey, cast(count(*) as int) as n from customer group by 1"),
    "fn_json": (lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k")), "select event_id, cast(json_extract_string(props, '$.k') as int) as k from events"),
    "fn_struct": (lambda s, d: t(s, d, "nation").select(F.struct("n_nationkey", "n_name").alias("s")).select("s.n_nationkey", F.col("s.n_name").alias("name")), "select n_nationkey, n_name as name from nation"),
    "fn_cosine": (lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("n")), "select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 6) as n from embeddings"),
    "stream_windowed_counts": (lambda s, d: windowed_counts(t(s, d, "events")), "select date_trunc('hour', ts) as start, event_type, count(*) as n from events group by 1, 2"),
}
