"""Kernels against brute force, the worked gaps, and the query analysis."""

import random
from itertools import product

import pytest

from patternjoin.kernel.gap import INF, Counters, Intervals, Options, SortedAtom, gap_count, gap_join
from patternjoin.kernel.intersect import leap, trie_join
from patternjoin.query import model as M
from patternjoin.query import patterns as P
from patternjoin.query.bounds import cover_bound


def brute(atoms, order, filters=()):
    domain = sorted({v for _, rows in atoms for r in rows for v in r})
    sets = [(names, set(rows)) for names, rows in atoms]
    ops = {"<": lambda a, b: a < b, "!=": lambda a, b: a != b}
    out = []
    for point in product(domain, repeat=len(order)):
        b = dict(zip(order, point))
        if all(tuple(b[v] for v in names) in rows for names, rows in sets) and all(ops[o](b[x], b[y]) for x, o, y in filters):
            out.append(point)
    return out


SHAPES = [P.path(3), P.tree1(), P.comb2(), P.clique(3), P.cycle4(), P.triangle3(), P.five_atoms(), P.lollipop(2),
          M.JoinQuery.of(("t", "a", "b", "c"), ("e", "b", "c"), ("v1", "c"))]


@pytest.mark.parametrize("seed", range(60))
def test_joins_equal_brute_force(seed):
    g = random.Random(seed)
    q = SHAPES[seed % len(SHAPES)]
    size = g.randint(2, 4 if len(q.variables) >= 5 else 7)
    rels = {}
    for a in q.atoms:
        rels.setdefault(a.rel, [tuple(g.randrange(size) for _ in a.vars) for _ in range(g.randint(0, 3 * size))])
    atoms = [(a.vars, rels[a.rel]) for a in q.atoms]
    orders = [M.choose_order(q), tuple(g.sample(q.variables, len(q.variables)))]
    for order in orders:
        expected = brute(atoms, order, q.filters)
        assert list(trie_join(atoms, order, q.filters)) == expected
        if not q.filters:
            assert gap_count(atoms, order) == len(expected)
        kept = M.skeleton(q, order)[0]
        for options in (Options(), Options(False, False, False), Options(cyclic="closure"), Options(complete_nodes=False), Options(frontier=False)):
            c, boxes = Counters(), []
            got = list(gap_join(atoms, order, kept, options, c, q.filters, boxes))
            assert got == expected, (q, order, options)
            for pattern, lo, hi in boxes:  # no stored box holds an output
                for point in brute(atoms, order):
                    assert not (all(p is None or p == x for p, x in zip(pattern, point)) and lo < point[len(pattern)] < hi)


def test_saved_seeks_never_change_results():
    g = random.Random(3)
    rows = sorted({(g.randrange(20), g.randrange(20)) for _ in range(90)})
    atoms = [(("a", "b"), rows), (("b", "c"), rows), (("c", "d"), rows)]
    on, off = Counters(), Counters()
    a = list(gap_join(atoms, ("a", "b", "c", "d"), None, Options(), on))
    b = list(gap_join(atoms, ("a", "b", "c", "d"), None, Options(reuse_gap_origin=False), off))
    assert a == b and on.seeks < off.seeks and on.seeks_saved > 0


def test_leap():
    assert list(leap([[1, 3, 4, 9], [3, 4, 5, 9], [0, 3, 9]])) == [3, 9]
    assert list(leap([[1], []])) == []
    assert list(leap([[2, 5]])) == [2, 5]


def test_intervals():
    s = Intervals()
    s.insert(9, 10)
    assert s.lo == []
    s.insert(1, 3)
    s.insert(3, 9)
    assert (s.lo, s.hi) == ([1, 3], [3, 9]) and s.free_from(2) == 3 and s.free_from(3) == 3 and s.free_from(4) == 9
    s.insert(2, 5)
    assert (s.lo, s.hi) == ([1], [9])
    s.insert(-INF, 2)
    assert s.free_from(-5) == 9
    g = random.Random(1)
    for _ in range(200):
        s, covered = Intervals(), set()
        for _ in range(8):
            lo = g.randint(-2, 30)
            hi = lo + g.randint(0, 8)
            s.insert(lo, hi)
            covered |= set(range(lo + 1, hi))
        for x in range(31):
            assert s.free_from(x) == next(y for y in range(x, 99) if y not in covered)


def test_worked_gaps():
    order = tuple("abcdefg")
    rel = SortedAtom(("b", "d", "e"), [(5, 1, 1), (7, 4, 2), (7, 9, 3), (10, 1, 1)], order)
    c = Counters()
    assert rel.gap_around([2, 6, 6, 1, 3, 7, 9], c, False) == ((None,), 5, 7)
    assert rel.gap_around([2, 7, 7, 5, 8, 8, 9], c, False) == ((None, 7, None), 4, 9)


def test_acyclicity_and_orders():
    tri = P.clique(3)
    assert not M.is_alpha_acyclic(tri) and not M.is_beta_acyclic(tri)
    covered = M.JoinQuery.of(("e", "a", "b"), ("e", "b", "c"), ("e", "a", "c"), ("t", "a", "b", "c"))
    assert M.is_alpha_acyclic(covered) and not M.is_beta_acyclic(covered)
    for q in (P.path(3), P.path(4), P.tree1(), P.tree2(), P.comb2(), P.five_atoms()):
        assert M.is_beta_acyclic(q) and M.is_neo(q, M.choose_order(q))
    assert not M.is_beta_acyclic(P.lollipop(2))
    q = M.JoinQuery.of(("e", "A", "B"), ("e", "B", "C"), ("e", "C", "D"), ("e", "D", "E"))
    depth = {"ABCDE": 5, "BACDE": 4, "BCADE": 4, "CBADE": 3, "CBDAE": 3}
    for o, d in depth.items():
        assert M.is_neo(q, tuple(o)) and M.elimination_depth(q, tuple(o)) == d
    for o in ("ABDCE", "BADCE"):
        assert not M.is_neo(q, tuple(o))
    assert M.choose_order(q) == tuple("ABCDE")
    tree, core = M.split_core(P.lollipop(2))
    assert len(core) == 3 and len(tree) == 3
    kept, skipped = M.skeleton(P.clique(4), tuple(P.clique(4).variables))
    assert kept and skipped


def test_bounds():
    n = 1000
    bound, weights = cover_bound(P.triangle3(), {"r": n, "s": n, "t": n})
    assert bound == pytest.approx(n**1.5) and weights == [0.5] * 3
    assert cover_bound(P.triangle3(), {"r": 1, "s": n, "t": n})[0] == pytest.approx(n)
    assert cover_bound(P.clique(4), {"e": n})[0] == pytest.approx(n**2)
    assert cover_bound(P.triangle3(), {"r": 0, "s": n, "t": n})[0] == 0


def test_parser():
    q = M.parse_pattern("e(x, y) & e(y, z) & x < y")
    assert str(q) == "e(x, y) & e(y, z) & x < y"
    for bad in ("e(x", "x < y", "e(x,y) & q < r", ""):
        with pytest.raises(ValueError):
            M.parse_pattern(bad)
