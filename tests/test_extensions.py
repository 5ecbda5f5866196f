"""Recursion and replayed streams against plain recounts."""

import heapq
import random

import pytest

from patternjoin.functions.extensions import EXTENSIONS
from patternjoin.graph import build as G
from patternjoin.operators import recursive as R
from patternjoin.streaming import replays

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def arcs():
    g = random.Random(9)
    return sorted({(a, b) for a, b in ((g.randrange(30), g.randrange(30)) for _ in range(45)) if a != b})


def nearest(arcs, start, weight):
    best, heap = {}, [(0, start)]
    while heap:
        d, v = heapq.heappop(heap)
        if v not in best:
            best[v] = d
            for a, b in arcs:
                if a == v:
                    heapq.heappush(heap, (d + weight(a, b), b))
    return best


def test_paths(spark, arcs):
    start = spark.createDataFrame([(arcs[0][0],)], "node long")
    e = spark.createDataFrame(arcs, "src long, dst long")
    assert {r["node"]: r["dist"] for r in R.bfs(e, start).collect()} == nearest(arcs, arcs[0][0], lambda a, b: 1)
    w = spark.createDataFrame([(a, b, a * b % 7 + 1) for a, b in arcs], "src long, dst long, w long")
    assert {r["node"]: r["dist"] for r in R.shortest_paths(w, start).collect()} == nearest(arcs, arcs[0][0], lambda a, b: a * b % 7 + 1)
    assert R.bfs(e, start.limit(0)).count() == 0


def test_components_and_ranks(spark, arcs):
    both = arcs + [(b, a) for a, b in arcs]
    chain = [(100 + i, 101 + i) for i in range(9)]
    e = spark.createDataFrame(arcs + chain + [(200, 200)], "src long, dst long")
    want = {v: min(nearest(both, v, lambda a, b: 1)) for v in {x for p in arcs for x in p}} | {100 + i: 100 for i in range(10)} | {200: 200}
    assert {r["node"]: r["component"] for r in R.components(e).collect()} == want
    ranks = [r["rank"] for r in R.pagerank(e, 3).collect()]
    assert sum(ranks) == pytest.approx(1) and len(ranks) == len(want)
    none = spark.createDataFrame([], "src long, dst long")
    assert R.components(none).count() == R.pagerank(none, 2).count() == 0


def test_late_rows_go(spark):
    first = replays.late(spark, D).selectExpr("min(start) as s").first()["s"]
    assert str(first)[:10] == "2024-01-02"  # the first day came last


def test_frequent_lines_and_hrefs_count(spark, tmp_path):
    n = 1_050
    shared = "a line of twenty letters and more"
    spark.createDataFrame([(i, f"own line of this one document {i}\n{shared}") for i in range(n)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    pages = [(i, '<a href="/all">') for i in range(n)] + [(5_000, '<a href="/b">'), (5_001, '<a href="/b">')]
    spark.createDataFrame(pages, "page_id long, html string").write.parquet(str(tmp_path / "pages.parquet"))
    assert G.doc_share(spark, str(tmp_path)).count() == n * (n - 1) // 2
    assert G.page_share(spark, str(tmp_path)).count() == n * (n - 1) // 2 + 1
    found = {r["node"]: r["component"] for r in EXTENSIONS["rec_components"][0](spark, str(tmp_path)).collect()}
    assert found == dict.fromkeys(range(n), 0) | {5_000: 5_000, 5_001: 5_000}


def test_skeleton_ablation_runs_on_its_graph(spark):
    from patternjoin.queries import QUERIES

    (want,) = QUERIES["clique3_prefix_copurchase_ret"](spark, D).collect()
    got = {r["variant"]: r["cnt"] for r in QUERIES["ablation_skeleton_clique3_copurchase_ret"](spark, D).collect()}
    assert got == {"closure": want["cnt"], "skeleton": want["cnt"]}


def test_registered_paths_have_no_bound(spark, tmp_path):
    """A chain of 40 arcs: its last nodes are farther than 60."""
    rows = [(k, k, f"2024-01-01 00:{k:02d}:00") for k in range(41)]
    spark.createDataFrame(rows, "event_id long, user_id long, ts string").selectExpr("event_id", "user_id", "cast(ts as timestamp_ntz) as ts").write.parquet(str(tmp_path / "events.parquet"))
    want = nearest([(k, k + 1) for k in range(40)], 0, lambda a, b: (a * 7 + b * 13) % 10 + 1)
    assert max(want.values()) > 60
    assert {r["node"]: r["dist"] for r in EXTENSIONS["rec_shortest_path"][0](spark, str(tmp_path)).collect()} == want
