"""Counts over packed blocks: the same as by joins, whatever the cells, and no wedge leaves a cell."""

import numpy as np
import pytest

from patternjoin.graph import build as G
from patternjoin.operators import blocks, pairwise
from patternjoin.operators import prefix as X
from patternjoin.queries import QUERIES
from patternjoin.query import patterns as P

D = "/root/testdata/sf0.001"


def cnt(df):
    return int(df.first()["cnt"])


def test_pack_keeps_every_arc_once():
    rng = np.random.default_rng(1)
    for low, high in ((0, 50), (10**12, 10**12 + 60), (-40, 40)):
        src, dst = rng.integers(low, high, (2, 900))
        n, data = blocks.pack(src, dst)
        own, many, other = blocks.unpack(data)
        got = list(zip(np.repeat(own, many).tolist(), other.tolist(), strict=True))
        assert got == sorted(set(zip(src.tolist(), dst.tolist(), strict=True))) and n == len(got)


@pytest.mark.parametrize("groups", (1, 3, 4))
def test_counts_do_not_depend_on_the_cells(spark, monkeypatch, groups):
    star = [(0, i) for i in range(1, 60)] + [(i, j) for i in range(1, 60) for j in (i + 1, i + 2, i + 7, i * 3 % 60) if i < j < 60]
    arcs = spark.createDataFrame(star + star[:40], "src long, dst long")
    e = {"e": arcs.distinct().persist()}
    monkeypatch.setattr(blocks, "_fitting", lambda *_: groups)
    for k in (3, 4):
        want = cnt(X.prefix_join(P.clique(k), e))
        assert want > 50
        for order in ("id", "degree"):
            assert cnt(blocks.clique_count(arcs, k, order)) == want
    want = cnt(X.prefix_join(P.cycle4(), e, P.cycle4().variables))
    assert cnt(blocks.square_count(arcs, "pairwise")) == cnt(blocks.square_count(arcs, "probing")) == want > 50
    assert cnt(blocks.clique_count(arcs.limit(0), 3)) == cnt(blocks.square_count(arcs.limit(0), "pairwise")) == 0


def test_classes_count_as_their_documents(spark, tmp_path):
    a, b, c = ("a line of twenty letters and more", "one more line of twenty letters", "the third line of twenty letters")
    texts = [a, a, f"{a}\n{b}", f"{b}\n{a}", f" {b}", f"{b}\n{c}", c, c, c, "only this one has this line of text", None, f"{a}\nshort"]
    rows = [(i, t) for i, t in enumerate(texts)] + [(6, b), (None, a)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    want = cnt(X.prefix_join(P.clique(3), {"e": G.doc_share(spark, str(tmp_path))}))
    assert cnt(QUERIES["clique3_prefix_doc_share"](spark, str(tmp_path))) == want > 20


def test_one_frequent_line_makes_no_pairs(spark, tmp_path, monkeypatch):
    """All its documents are one class: the pairs of 2,000 documents were formed before."""
    line = "a line of twenty letters and more"
    spark.createDataFrame([(i, line) for i in range(2_000)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    monkeypatch.setattr(G, "doc_share", None)
    assert cnt(QUERIES["clique3_prefix_doc_share"](spark, str(tmp_path))) == 2_000 * 1_999 * 1_998 // 6


@pytest.mark.parametrize("hubs, types", ((0, 9), (1, 9), (3, 9), (126, 9), (126, 400)))
def test_hub_lines_make_types_and_no_pairs(spark, monkeypatch, hubs, types):
    """Links of frequent lines are not listed, and triangles of hub and other links are all counted."""
    rng = np.random.default_rng(4)
    held = {frozenset(f"line {k}" for k in range(12) if rng.random() < (0.35 if k < 5 else 0.08)) for _ in range(160)} - {frozenset()}
    held = {ls: int(rng.integers(1, 4)) for ls in sorted(held, key=sorted)}
    classes = spark.createDataFrame([(i, w, [x.encode() for x in sorted(ls)]) for i, (ls, w) in enumerate(held.items())], "node long, w long, ls array<binary>")
    docs = [ls for ls, w in held.items() for _ in range(w)]
    linked = np.array([[i != j and bool(a & b) for j, b in enumerate(docs)] for i, a in enumerate(docs)], np.int64)
    monkeypatch.setattr(blocks, "HUB_CLASSES", 8)
    monkeypatch.setattr(blocks, "TYPES", types)
    monkeypatch.setattr(blocks, "TYPE_BLOCK", 7)
    listed = []
    monkeypatch.setattr(blocks, "_pairs", lambda rows, *a: listed.append(rows.select("l").distinct().count()) or G._pairs(rows, *a))
    assert cnt(blocks.class_triangles(classes, hubs)) == np.trace(linked @ linked @ linked) // 6 > 1_000
    assert (listed[0] < 12) == (hubs > 0)


def unfolded(*_, **__):
    raise AssertionError("wedges are unfolded by Spark")


@pytest.mark.parametrize("name", ["cycle4_pairwise_copurchase", "cycle4_probing_copurchase", "clique4_prefix_degree_copurchase", "clique3_pairwise_copurchase"])
def test_registered_counts_leave_no_wedge(spark, monkeypatch, name):
    e = {"e": G.copurchase(spark, D)}
    q = P.SHAPES[name.split("_")[0]]()
    want = cnt(X.prefix_join(q, e, q.variables))
    for module, join in ((pairwise, "pairwise_join"), (X, "probing_join"), (X, "prefix_join")):
        monkeypatch.setattr(module, join, unfolded)
    assert cnt(QUERIES[name](spark, D)) == want > 0
