"""Join queries as values: atoms, filters, and what their hypergraph says about them."""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import permutations


@dataclass(frozen=True)
class Atom:
    rel: str
    vars: tuple[str, ...]


@dataclass(frozen=True)
class JoinQuery:
    """A natural join of atoms over shared variables, with comparisons between variables."""

    atoms: tuple[Atom, ...]
    filters: tuple[tuple[str, str, str], ...] = ()

    @staticmethod
    def of(*atoms: tuple, filters: tuple = ()) -> JoinQuery:
        return JoinQuery(tuple(Atom(a[0], tuple(a[1:])) for a in atoms), tuple(filters))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.atoms for v in a.vars))

    @property
    def edges(self) -> tuple[frozenset, ...]:
        return tuple(frozenset(a.vars) for a in self.atoms)

    def __str__(self) -> str:
        parts = [f"{a.rel}({', '.join(a.vars)})" for a in self.atoms] + [f"{a} {op} {b}" for a, op, b in self.filters]
        return " & ".join(parts)


def parse_pattern(text: str) -> JoinQuery:
    """`e(x, y) & e(y, z) & x < y` as a query."""
    atoms, filters = [], []
    for part in filter(None, (p.strip() for p in text.split("&"))):
        if m := re.fullmatch(r"(\w+)\s*\(\s*(\w+(?:\s*,\s*\w+)*)\s*\)", part):
            atoms.append(Atom(m[1], tuple(v.strip() for v in m[2].split(","))))
        elif m := re.fullmatch(r"(\w+)\s*(<=|>=|<|>|!=)\s*(\w+)", part):
            filters.append((m[1], m[2], m[3]))
        else:
            raise ValueError(f"neither an atom nor a comparison: {part!r}")
    q = JoinQuery(tuple(atoms), tuple(filters))
    unknown = {v for f in filters for v in (f[0], f[2])} - set(q.variables)
    if unknown or not atoms:
        raise ValueError(f"variables without an atom: {sorted(unknown)}" if atoms else "a pattern needs an atom")
    return q


# ---------------------------------------------------------------- acyclicity


def join_tree(q: JoinQuery) -> list[tuple[int, int | None]] | None:
    """(atom, parent) with children before parents, by removing ears; None if the query is cyclic."""
    left, out = dict(enumerate(q.edges)), []
    while len(left) > 1:
        ear = None
        for i, e in left.items():
            others = [j for j in left if j != i]
            shared = e & frozenset().union(*(left[j] for j in others))
            host = next((j for j in others if shared <= left[j]), None)
            if host is not None and (shared or not any(e & left[j] for j in others)):
                ear = (i, host)
                break
        if ear is None:
            return None
        out.append(ear)
        del left[ear[0]]
    return out + [(next(iter(left)), None)]


def is_alpha_acyclic(q: JoinQuery) -> bool:
    return join_tree(q) is not None


def is_chain(sets: list[frozenset]) -> bool:
    s = sorted(sets, key=len)
    return all(a <= b for a, b in zip(s, s[1:], strict=False))


def is_beta_acyclic(q: JoinQuery) -> bool:
    """Repeatedly drop a variable whose edges form a chain."""
    edges, left = [set(e) for e in q.edges], set(q.variables)
    while left:
        v = next((v for v in sorted(left) if is_chain([frozenset(e) for e in edges if v in e])), None)
        if v is None:
            return False
        left.discard(v)
        for e in edges:
            e.discard(v)
    return True


# ---------------------------------------------------------------- variable orders


def is_neo(q: JoinQuery, order: tuple[str, ...]) -> bool:
    """Each variable's edges, cut down to the variables up to it, form a chain."""
    return all(is_chain([e & frozenset(order[:k + 1]) for e in q.edges if v in e]) for k, v in enumerate(order))


def nested_elimination_orders(q: JoinQuery) -> list[tuple[str, ...]]:
    if len(q.variables) > 8:
        raise ValueError("more than 8 variables; give an order")
    return [o for o in permutations(q.variables) if is_neo(q, o)]


def elimination_depth(q: JoinQuery, order: tuple[str, ...]) -> int:
    """Longest path from a root to a leaf of the elimination tree."""
    depth: dict[str, int] = {}
    for k, v in enumerate(order):
        above = set().union(*(e & set(order[:k]) for e in q.edges if v in e))
        depth[v] = 1 + (depth[max(above, key=order.index)] if above else 0)
    return max(depth.values())


def elimination_width(q: JoinQuery, order: tuple[str, ...]) -> int:
    """Most earlier variables that a variable meets when later ones are eliminated."""
    edges, width = [set(e) for e in q.edges], 0
    for v in reversed(order):
        bag = set().union(*(e for e in edges if v in e)) - {v}
        width = max(width, len(bag))
        edges = [e for e in edges if v not in e] + [bag]
    return width


def choose_order(q: JoinQuery, cyclic: bool | None = None, stats: dict[str, int] | None = None) -> tuple[str, ...]:
    """Beta-acyclic: the nested elimination order with the longest elimination path, ties by the
    smallest variables first. Otherwise: as many bound atoms as possible for each prefix."""
    stats = stats or {}
    size = lambda v: stats.get(v, 1 << 40)
    if cyclic is None:
        cyclic = not is_beta_acyclic(q)
    if not cyclic and len(q.variables) <= 8:
        found = nested_elimination_orders(q)
        return min(found, key=lambda o: (-elimination_depth(q, o), [size(v) for v in o], [q.variables.index(v) for v in o]))
    order: list[str] = []
    while len(order) < len(q.variables):
        def gain(v):
            closed = sum(set(e) <= {*order, v} for e in q.edges)
            touching = sum(v in e and bool(e & set(order)) for e in q.edges)
            return (-touching if order else 0, -closed, size(v), -sum(v in e for e in q.edges), q.variables.index(v))
        order.append(min((v for v in q.variables if v not in order), key=gain))
    return tuple(order)


def skeleton(q: JoinQuery, order: tuple[str, ...], sizes: dict[str, int] | None = None) -> tuple[list[int], list[int]]:
    """(kept, skipped) atoms: greedily the small atoms first, as long as the order stays nested."""
    kept: list[int] = []
    rank = sorted(range(len(q.atoms)), key=lambda i: ((sizes or {}).get(q.atoms[i].rel, 0), min(order.index(v) for v in q.atoms[i].vars), i))
    for i in rank:
        if is_neo(JoinQuery(tuple(q.atoms[j] for j in sorted([*kept, i]))), tuple(v for v in order)):
            kept.append(i)
    return sorted(kept), [i for i in range(len(q.atoms)) if i not in kept]


def specialises(p: tuple, q: tuple) -> bool:
    """Pattern p (constants and None) fixes at least what q fixes, with the same values."""
    return all(b is None or a == b for a, b in zip(p, q, strict=True))


def split_core(q: JoinQuery) -> tuple[list[int], list[int]]:
    """(tree atoms, core atoms): ears are peeled off until only the cyclic core is left."""
    left = dict(enumerate(q.edges))
    peeled: list[int] = []
    while True:
        ear = None
        for i, e in left.items():
            rest = frozenset().union(*(x for j, x in left.items() if j != i))
            shared = e & rest
            if len(shared) <= 1 and len(e) <= 2 and (e - shared or len(e) == 1):
                ear = i
                break
        if ear is None or len(left) == 1:
            return peeled, sorted(left)
        peeled.append(ear)
        del left[ear]
