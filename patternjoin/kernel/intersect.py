"""Trie-intersection join over sorted tuples: the task-local form of the worst-case-optimal join."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np

Rows = list[tuple[int, ...]]


class Trie:
    """A relation's rows as nested sorted lists, in the order of its variables."""

    __slots__ = ("children", "values")

    def __init__(self, rows: Rows, depth: int = 0):
        self.values: list[int] = []
        self.children: list[Trie] = []
        if not rows or depth == len(rows[0]):
            return
        groups: dict[int, Rows] = {}
        for r in rows:
            groups.setdefault(r[depth], []).append(r)
        self.values = sorted(groups)
        self.children = [Trie(groups[v], depth + 1) for v in self.values]

    def child(self, value: int) -> Trie | None:
        i = bisect_left(self.values, value)
        return self.children[i] if i < len(self.values) and self.values[i] == value else None


def leap(lists: list[list[int]]) -> Iterator[int]:
    """Values that all sorted lists hold: each cursor in turn seeks the largest value seen."""
    if any(not x for x in lists):
        return
    at, turn, agreed, high = [0] * len(lists), 0, 0, max(x[0] for x in lists)
    while True:
        x = lists[turn]
        at[turn] = i = bisect_left(x, high, at[turn])
        if i == len(x):
            return
        if x[i] == high:
            agreed += 1
            if agreed >= len(lists):
                yield high
                high += 1
                agreed = 0
        else:
            high, agreed = x[i], 1
        turn = (turn + 1) % len(lists)


def by_order(atoms: list[tuple[tuple[str, ...], Rows]], order: tuple[str, ...]) -> list[tuple[tuple[str, ...], Rows]]:
    """Columns of every relation in the order of the variables; repeated variables must agree."""
    out = []
    for names, rows in atoms:
        own = tuple(v for v in order if v in names)
        first = {v: names.index(v) for v in own}
        same = [(i, first[v]) for i, v in enumerate(names) if first[v] != i]
        out.append((own, sorted({tuple(r[first[v]] for v in own) for r in rows if all(r[i] == r[j] for i, j in same)})))
    return out


def trie_join(atoms, order: tuple[str, ...], filters: tuple = ()) -> Iterator[tuple[int, ...]]:
    """All bindings in lexicographic order: intersect a variable over its atoms, then go down for each value."""
    ordered = by_order(atoms, order)
    if any(not rows for _, rows in ordered):
        return
    tries = [Trie(rows) for _, rows in ordered]
    uses = [[i for i, (names, _) in enumerate(ordered) if v in names] for v in order]
    check = [[(order.index(a), op, order.index(b)) for a, op, b in filters if max(order.index(a), order.index(b)) == k] for k in range(len(order))]
    holds = {"<": int.__lt__, ">": int.__gt__, "<=": int.__le__, ">=": int.__ge__, "!=": int.__ne__}
    point: list[int] = [0] * len(order)

    def down(k: int, at: list[Trie]) -> Iterator[tuple[int, ...]]:
        if k == len(order):
            yield tuple(point)
            return
        for value in leap([at[i].values for i in uses[k]]):
            point[k] = value
            if all(holds[op](point[a], point[b]) for a, op, b in check[k]):
                below = list(at)
                for i in uses[k]:
                    below[i] = at[i].child(value)
                yield from down(k + 1, below)

    yield from down(0, tries)


#: Candidates that are looked at together.
FLAT_STEP = 200_000


def sorted_set(x: np.ndarray) -> np.ndarray:
    """Different values in order, of an array that is no longer needed: by sorting, as numpy's own way hashes them first, at ten times the time."""
    x.sort()
    return x[np.flatnonzero(np.append(True, x[1:] != x[:-1]))] if len(x) else x


def flat_count(atoms: list[tuple[tuple[str, ...], list[np.ndarray]]], order: tuple[str, ...], filters: tuple = ()) -> int:
    """The number of bindings over atoms of one or two variables, given as columns: 8 bytes a tuple.

    A relation is one sorted array of coded pairs, its trie in flat form. Prefixes are extended by the next
    variable many at a time, each from the atom with the fewest candidates; the others are probed.
    """
    domain = sorted_set(np.concatenate([c for _, columns in atoms for c in columns]))
    d = len(domain)
    if not d or any(not len(columns[0]) for _, columns in atoms):
        return 0
    allowed = {v: np.ones(d, bool) for v in order}
    pairs: list[tuple[str, str, np.ndarray]] = []
    for names, columns in atoms:
        codes = [np.searchsorted(domain, c) for c in columns]
        for v, c in zip(names, codes, strict=True):
            allowed[v] &= np.bincount(c, minlength=d) > 0
        if len(names) == 2:
            u, v = sorted((0, 1), key=lambda i: order.index(names[i]))
            pairs.append((names[u], names[v], sorted_set(codes[u] * d + codes[v])))
    holds = {"<": np.less, ">": np.greater, "<=": np.less_equal, ">=": np.greater_equal, "!=": np.not_equal}
    hooks = [[(u, rows) for u, v, rows in pairs if v == x] for x in order]
    checks = [[f for f in filters if max(order.index(f[0]), order.index(f[2])) == k] for k in range(len(order))]

    def kept(k: int, prefix: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        ok = allowed[order[k]][prefix[order[k]]]
        for a, op, b in checks[k]:
            ok &= holds[op](prefix[a], prefix[b])
        return {v: x[ok] for v, x in prefix.items()}

    def down(k: int, prefix: dict[str, np.ndarray]) -> int:
        n = len(next(iter(prefix.values())))
        if k == len(order) or not n:
            return n
        if not hooks[k]:
            every = np.flatnonzero(allowed[order[k]])
            step = max(1, FLAT_STEP // max(1, len(every)))
            return sum(down(k + 1, kept(k, {v: np.repeat(x[lo:lo + step], len(every)) for v, x in prefix.items()}
                                        | {order[k]: np.tile(every, len(range(n)[lo:lo + step]))})) for lo in range(0, n, step))
        lows = np.stack([np.searchsorted(rows, prefix[u] * d) for u, rows in hooks[k]])
        sizes = np.stack([np.searchsorted(rows, (prefix[u] + 1) * d) for u, rows in hooks[k]]) - lows
        best, total = np.argmin(sizes, axis=0), 0
        for i, (_, rows) in enumerate(hooks[k]):
            mine = np.flatnonzero((best == i) & (sizes[i] > 0))
            ends = np.cumsum(sizes[i][mine])
            lo = 0
            while lo < len(mine):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + FLAT_STEP, "right")))
                some, many = mine[lo:hi], sizes[i][mine[lo:hi]]
                at = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many) + np.repeat(lows[i][some], many)
                longer = {v: np.repeat(x[some], many) for v, x in prefix.items()} | {order[k]: rows[at] % d}
                for j, (u, other) in enumerate(hooks[k]):
                    if j != i and len(longer[u]):
                        key = longer[u] * d + longer[order[k]]
                        found = other[np.minimum(np.searchsorted(other, key), len(other) - 1)] == key
                        longer = {v: x[found] for v, x in longer.items()}
                total += down(k + 1, kept(k, longer))
                lo = hi
        return total

    starts = np.flatnonzero(allowed[order[0]])
    return sum(down(1, kept(0, {order[0]: starts[lo:lo + FLAT_STEP]})) for lo in range(0, len(starts), FLAT_STEP))
