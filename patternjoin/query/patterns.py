"""The query shapes of the experiments, over a binary relation and node samples."""

from __future__ import annotations

from .model import JoinQuery


def clique(k: int, rel: str = "e", ordered: bool = True) -> JoinQuery:
    v = [f"x{i}" for i in range(k)]
    atoms = [(rel, v[i], v[j]) for i in range(k) for j in range(i + 1, k)]
    return JoinQuery.of(*atoms, filters=tuple((v[i], "<", v[i + 1]) for i in range(k - 1)) if ordered else ())


def cycle4(rel: str = "e") -> JoinQuery:
    """The square whose corners increase all the way round."""
    return JoinQuery.of((rel, "x0", "x1"), (rel, "x1", "x2"), (rel, "x2", "x3"), (rel, "x0", "x3"),
                        filters=(("x0", "<", "x1"), ("x1", "<", "x2"), ("x2", "<", "x3")))


def cycle4_full(rel: str = "e") -> JoinQuery:
    """Every square once: its smallest corner first, the neighbours of that corner in order."""
    return JoinQuery.of((rel, "x0", "x1"), (rel, "x1", "x2"), (rel, "x2", "x3"), (rel, "x0", "x3"),
                        filters=(("x0", "<", "x1"), ("x0", "<", "x2"), ("x1", "<", "x3")))


def path(k: int, rel: str = "e") -> JoinQuery:
    return JoinQuery.of(("v1", "x0"), ("v2", f"x{k}"), *[(rel, f"x{i}", f"x{i + 1}") for i in range(k)])


def tree1(rel: str = "e") -> JoinQuery:
    return JoinQuery.of((rel, "r", "a"), (rel, "r", "b"), ("v1", "a"), ("v2", "b"))


def tree2(rel: str = "e") -> JoinQuery:
    leaves = [("v1", "a"), ("v2", "b"), ("v3", "c"), ("v4", "d")]
    return JoinQuery.of((rel, "r", "p"), (rel, "r", "q"), (rel, "p", "a"), (rel, "p", "b"), (rel, "q", "c"), (rel, "q", "d"), *leaves)


def comb2(rel: str = "e") -> JoinQuery:
    return JoinQuery.of((rel, "r", "a"), (rel, "r", "p"), (rel, "p", "b"), ("v1", "a"), ("v2", "b"))


def lollipop(k: int, rel: str = "e") -> JoinQuery:
    """A path of k edges from a sampled node, then a clique of k + 1 nodes on its end."""
    v = [f"x{i}" for i in range(2 * k + 1)]
    core = v[k:]
    return JoinQuery.of(("v1", "x0"), *[(rel, v[i], v[i + 1]) for i in range(k)],
                        *[(rel, core[i], core[j]) for i in range(k + 1) for j in range(i + 1, k + 1)])


def triangle3(r: str = "r", s: str = "s", t: str = "t") -> JoinQuery:
    return JoinQuery.of((r, "a", "b"), (s, "b", "c"), (t, "a", "c"))


def five_atoms() -> JoinQuery:
    return JoinQuery.of(("r1", "a", "b"), ("r2", "a", "c"), ("r3", "b", "d"), ("r4", "c"), ("r5", "d"))


SHAPES = {"clique3": lambda: clique(3), "clique4": lambda: clique(4), "cycle4": cycle4, "path3": lambda: path(3),
          "path4": lambda: path(4), "tree1": tree1, "tree2": tree2, "comb2": comb2, "lollipop2": lambda: lollipop(2),
          "lollipop3": lambda: lollipop(3)}
