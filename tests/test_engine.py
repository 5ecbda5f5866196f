"""Methods agree with each other and with pinned counts on the smallest tables."""

import pytest
from pyspark.sql import functions as F

from patternjoin.graph import build as G
from patternjoin.operators import acyclic as A
from patternjoin.operators import cells, pairwise
from patternjoin.operators import prefix as X
from patternjoin.plans.chooser import evaluate, explain_pattern, plan_pattern
from patternjoin.query import patterns as P
from patternjoin.query.model import JoinQuery
from patternjoin.streaming.views import replayed_triangles

D = "/root/testdata/sf0.001"


def cnt(df):
    return int(df.first()["cnt"])


@pytest.fixture(scope="module")
def ret(spark):
    return G.copurchase_ret(spark, D).persist()


def test_pinned_cyclic_counts(spark, ret):
    for q, n in ((P.clique(3), 830), (P.clique(4), 180), (P.cycle4(), 1438)):
        rels = {"e": ret}
        assert cnt(X.prefix_join(q, rels, q.variables)) == cnt(pairwise.pairwise_join(q, rels)) == n
        assert cnt(cells.hypercube_join(q, rels, cells=8)) == cnt(cells.partitioned_gap_join(q, rels, parts=2, granularity=2)) == n
    assert cnt(X.cycles4_by_wedges(ret)) == 4327
    assert cnt(X.gas_triangles(ret)) == cnt(X.heavy_light_triangles(ret, 12)) == cnt(X.prefix_join(P.clique(3), {"e": ret}, orient="degree")) == 830
    assert X.triangles_by_node(ret).agg(F.sum("triangles")).first()[0] == 3 * 830
    with pytest.raises(ValueError):
        X.prefix_join(P.cycle4(), {"e": ret}, orient="degree")


def test_pinned_sampled_counts(spark, ret):
    e = G.symmetric(ret).persist()
    rels = {"e": e} | G.samples(e, 8)
    for shape, n in (("path3", 8981), ("path4", 129821), ("tree1", 536), ("tree2", 526705), ("comb2", 8981)):
        assert cnt(A.message_count(P.SHAPES[shape](), rels)) == n
    assert cnt(A.hybrid_join(P.lollipop(2), rels)) == 155500 and cnt(A.hybrid_join(P.lollipop(3), rels)) == 2094378
    assert cnt(A.acyclic_join(P.path(3), rels)) == cnt(pairwise.bushy_path(3, rels)) == cnt(pairwise.leftdeep_path(3, rels)) == 8981
    assert A.hybrid_join(P.lollipop(2), {"e": e} | G.samples(e, 80), "rows").count() == 15720


def test_edge_cases(spark):
    empty = spark.createDataFrame([], "src long, dst long")
    few = spark.createDataFrame([(1, 2), (2, 3), (1, 3), (1, 3), (3, 3), (None, 1)], "src long, dst long").distinct()
    one = spark.createDataFrame([(1,)], "node long")
    none = spark.createDataFrame([], "node long")
    assert cnt(X.prefix_join(P.clique(3), {"e": empty})) == cnt(pairwise.pairwise_join(P.clique(3), {"e": empty})) == 0
    assert cnt(X.prefix_join(P.clique(3), {"e": few})) == cnt(pairwise.bruteforce(P.clique(3), {"e": few})) == 1
    assert cnt(A.message_count(P.path(3), {"e": few, "v1": one, "v2": none})) == 0
    loop = JoinQuery.of(("e", "x", "x"))
    assert cnt(pairwise.pairwise_join(loop, {"e": few})) == 1
    apart = JoinQuery.of(("e", "a", "b"), ("v1", "c"))
    assert cnt(pairwise.pairwise_join(apart, {"e": few, "v1": one})) == cnt(A.message_count(apart, {"e": few, "v1": one})) == 4


def test_delta_equals_recount(spark, ret):
    old, new = ret.where("(src + dst) % 3 <> 0"), ret
    for q in (P.clique(3), P.cycle4()):
        assert cnt(X.prefix_join(q, {"e": old}, q.variables)) + cnt(A.delta_count(q, old, new)) == cnt(X.prefix_join(q, {"e": ret}, q.variables))


def test_planner(spark, ret):
    assert [plan_pattern(P.SHAPES[s]()).method for s in ("clique3", "cycle4", "path3", "tree2", "lollipop2")] == ["prefix", "prefix", "messages", "messages", "hybrid"]
    text = explain_pattern(P.clique(3), {"e": ret}, {"e": 1220})
    assert "CartesianProduct" not in text and "prefix" in text
    assert cnt(evaluate(P.clique(3), {"e": ret})) == 830


def test_streaming_view(spark):
    assert cnt(replayed_triangles(spark, D)) == 455


def test_bloom_filter_is_in_the_plan_before_the_exchange(spark, ret):
    rels = {"e": G.symmetric(ret)} | G.samples(G.symmetric(ret), 8)
    held = A.full_reduce(P.path(3), rels, bloom=True)
    plan = held[0]._jdf.queryExecution().executedPlan().toString()
    assert "Subquery" in plan and "shiftright" in plan
    assert "shiftright" not in A.full_reduce(P.path(3), rels)[0]._jdf.queryExecution().executedPlan().toString()
    few = spark.range(0, 100_000, 1000).toDF("a")
    kept = A.bloom_reduce(spark.range(100_000).toDF("a"), few)
    assert kept.join(few, "a").count() == 100 and kept.count() < 5_000
    assert A.bloom_reduce(few, few.limit(0)).count() == 0
    assert cnt(A.acyclic_join(P.path(3), rels, bloom=True)) == 8981


def test_counting_gap_box(spark, ret):
    e = G.symmetric(ret)
    rels = {"e": e} | G.samples(e, 8)
    for shape, n in (("path3", 8981), ("tree1", 536), ("tree2", 526705), ("comb2", 8981)):
        assert cnt(cells.partitioned_gap_join(P.SHAPES[shape](), rels, parts=2, points=True)) == n
    assert cnt(A.hybrid_join(P.lollipop(2), rels, path="gapbox")) == 155500
    with pytest.raises(ValueError):
        cells.partitioned_gap_join(P.clique(3), {"e": ret}, points=True)


def test_probing_join_with_a_hub(spark):
    star = [(0, i) for i in range(1, 400)] + [(i, i + 1) for i in range(1, 399)] + [(5, 9), (7, 3)]
    edges = G.unordered(spark.createDataFrame(star, "src long, dst long"))
    for q in (P.clique(3), P.clique(4), P.cycle4()):
        assert cnt(X.probing_join(q, {"e": edges}, q.variables)) == cnt(X.prefix_join(q, {"e": edges}, q.variables))


def test_measures(spark, ret):
    from patternjoin.plans import measures

    done = measures.timed(lambda: X.prefix_join(P.clique(3), {"e": ret}), timeout_s=300)
    assert done["status"] == "ok" and done["rows"][0]["cnt"] == 830 and done["seconds"] > 0
    late = measures.timed(lambda: spark.range(10**12).selectExpr("sum(hash(id)) as cnt"), timeout_s=1)
    assert late["status"] == "timeout" and late["seconds"] is None
    assert measures.speedup(4.0, 2.0) == 2.0 and measures.speedup(None, 2.0) is None
    assert measures.normalised({1: 2.0, 2: 1.0, 4: None}) == {1: 1.0, 2: 0.5, 4: None}
    cost = measures.explain_cost(pairwise.pairwise_join(P.clique(3), {"e": ret}))
    wcoj = measures.explain_cost(X.prefix_join(P.clique(3), {"e": ret}))
    assert cost["largest_intermediate_rows"] > 0 and cost["shuffle_bytes"] > 0 and wcoj["operators"] > 0
    assert measures.same_count({"a": 3, "b": 3}) and not measures.same_count({"a": 3, "b": 4})
