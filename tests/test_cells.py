"""Cells of the one-round joins stay small whatever the sizes of the relations."""

import numpy as np

from patternjoin.graph import build as G
from patternjoin.kernel.intersect import flat_count, trie_join
from patternjoin.operators import acyclic as A
from patternjoin.operators import cells, pairwise
from patternjoin.query import patterns as P
from patternjoin.query.model import choose_order

D = "/root/testdata/sf0.001"


def cnt(df):
    return int(df.first()["cnt"])


def test_shares_fit_a_cell():
    for q, sizes in ((P.path(3), [75_000, 75_000, 75_000, 6_000_000, 75_000]), (P.comb2(), [75_000, 6_000_000, 75_000, 75_000, 75_000]), (P.clique(3), [8_000_000] * 3)):
        of = cells.fitting_shares(q, sizes, 40_000)
        assert sum(n / cells._prod(of[v] for v in a.vars) for a, n in zip(q.atoms, sizes, strict=True)) <= 40_000
    assert cells.fitting_shares(P.path(3), [1] * 5, 40_000, {"x0": 4}) == {"x0": 4, "x1": 1, "x2": 1, "x3": 1}


def test_gap_cells_over_all_variables(spark, monkeypatch):
    e = G.symmetric(G.copurchase_ret(spark, D)).persist()
    rels = {"e": e} | G.samples(e, 8)
    for shape in ("path3", "tree1", "comb2"):
        q = P.SHAPES[shape]()
        want = cnt(A.message_count(q, rels))
        sizes = [0]
        cut = cells._join_cells

        def seen(q, dealt, *rest, sizes=sizes, cut=cut):
            sizes[0] = dealt.groupBy("cell").count().agg({"count": "max"}).first()[0]
            return cut(q, dealt, *rest)

        monkeypatch.setattr(cells, "_join_cells", seen)
        assert cnt(cells.partitioned_gap_join(q, rels, parts=2, points=True, cell_tuples=100)) == want
        assert sizes[0] < 300 < e.count()
        monkeypatch.setattr(cells, "_join_cells", cut)
    assert cnt(cells.partitioned_gap_join(P.path(3), rels, parts=2, cell_tuples=200)) == cnt(A.message_count(P.path(3), rels))
    monkeypatch.setattr(cells.partitioned_gap_join, "__defaults__", (*cells.partitioned_gap_join.__defaults__[:-1], 200))
    q = P.lollipop(2)
    assert cnt(A.hybrid_join(q, rels, path="gapbox")) == cnt(A.hybrid_join(q, rels))
    assert cnt(cells.partitioned_gap_join(P.clique(3), {"e": G.copurchase_ret(spark, D)}, parts=2, granularity=2)) == 830


def test_flat_counts():
    rng = np.random.default_rng(1)
    for q in (P.clique(3), P.clique(4), P.cycle4(), P.triangle3(), P.path(3), P.comb2()):
        rows = {a.rel: rng.integers(0, 12, (60, len(a.vars))) for a in q.atoms}
        atoms = [(a.vars, list(rows[a.rel].T)) for a in q.atoms]
        order = choose_order(q, cyclic=True)
        want = sum(1 for _ in trie_join([(v, [tuple(map(int, r)) for r in zip(*c, strict=True)]) for v, c in atoms], order, q.filters))
        assert flat_count(atoms, order, q.filters) == want


def test_hypercube_cells_grow_with_the_relations(spark, monkeypatch):
    e, most = G.copurchase_ret(spark, D).persist(), []
    cut = cells._join_cells
    monkeypatch.setattr(cells, "_join_cells", lambda q, dealt, *rest: (most.append(dealt.groupBy("cell").count().agg({"count": "max"}).first()[0]), cut(q, dealt, *rest))[1])
    for q, n in ((P.clique(3), 830), (P.cycle4(), 1438)):
        assert cnt(cells.hypercube_join(q, {"e": e}, cells=2, cell_tuples=500)) == n
    assert max(most) < 700 < 3 * e.count()


def test_hypercube_sends_packed_blocks(spark, monkeypatch):
    """A clique's tuples went to their cells one by one, a row each: now a row is a block, sent once to a cell."""
    rng = np.random.default_rng(2)
    e = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 90, (3_000, 2))], "src long, dst int").distinct().persist()
    other = spark.createDataFrame([(int(a), None if a == 5 else int(b)) for a, b in rng.integers(-40, 90, (900, 2))], "x int, y long").distinct().persist()
    sent, cut = [], cells._join_cells
    monkeypatch.setattr(cells, "_join_cells", lambda q, dealt, *rest: (sent.append((dealt.count(), dealt.dropDuplicates(["cell", "rel", "a", "b"]).count())), cut(q, dealt, *rest))[1])
    for q, rels in ((P.clique(4), {"e": e}), (P.cycle4(), {"e": e}), (P.triangle3(), {"r": e, "s": other, "t": e})):
        want = cnt(pairwise.pairwise_join(q, rels))
        for tuples in (700, 5_000):
            assert cnt(cells.hypercube_join(q, rels, cells=3, cell_tuples=tuples)) == want > 100
            assert sent[-1][0] == sent[-1][1] < e.count() * 6
