"""Gap-box join: collect the empty boxes of the output space until outputs and boxes cover it.

A box is a pattern (constants and wildcards over the first variables), one open interval on the
next variable and nothing after it. The gap tree keeps, for each pattern, the disjoint intervals
seen so far; the search asks it for the next point no box covers, asks every atom for the largest
gap around that point, and stores those gaps or emits the point.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from dataclasses import dataclass, fields

from .intersect import Rows, Trie, by_order

INF = 1 << 62


class Intervals:
    """Disjoint open integer intervals in one sorted ledger of ends.

    (1, 3) and (3, 9) stay apart, since 3 is free; an interval without an integer is ignored.
    """

    __slots__ = ("lo", "hi")

    def __init__(self):
        self.lo: list[int] = []
        self.hi: list[int] = []

    def insert(self, lo: int, hi: int) -> bool:
        """True if it took in other intervals."""
        if hi - lo < 2:
            return False
        i, j = bisect_right(self.hi, lo), bisect_left(self.lo, hi)
        merged = i < j
        if merged:
            lo, hi = min(lo, self.lo[i]), max(hi, self.hi[j - 1])
        self.lo[i:j], self.hi[i:j] = [lo], [hi]
        return merged

    def free_from(self, x: int) -> int:
        """The smallest value of at least x that no interval covers."""
        i = bisect_left(self.lo, x) - 1
        return self.hi[i] if i >= 0 and self.hi[i] > x else x

    def covers(self, x: int) -> bool:
        return self.free_from(x) != x


class Node:
    __slots__ = ("pattern", "gaps", "children", "star", "passes", "complete", "counts", "total")

    def __init__(self, pattern: tuple):
        self.pattern = pattern
        self.gaps = Intervals()
        self.children: dict[int, Node] = {}
        self.star: Node | None = None
        self.passes = 0
        self.complete = False
        self.counts: dict[int, int] = {}  # what the finished branches below a point of the ledger contribute; 1 where absent
        self.total = 0  # of a finished node: the sum over its points


class GapTree:
    def __init__(self):
        self.root = Node(())
        self.nodes = 1

    def at(self, pattern: tuple, create: bool = True) -> Node | None:
        node = self.root
        for p in pattern:
            nxt = node.star if p is None else node.children.get(p)
            if nxt is None:
                if not create or (p is not None and node.gaps.covers(p)):
                    return None  # nothing under a value that is ruled out anyway
                nxt = Node((*node.pattern, p))
                self.nodes += 1
                if p is None:
                    node.star = nxt
                else:
                    node.children[p] = nxt
            node = nxt
        return node

    def insert(self, pattern: tuple, lo: int, hi: int) -> bool:
        node = self.at(pattern)
        if node is None:
            return False
        merged = node.gaps.insert(lo, hi)
        # children inside the new interval are covered as a whole
        for v in [v for v in node.children if lo < v < hi]:
            del node.children[v]
        return merged

    @staticmethod
    def below(level: list[Node], value: int) -> list[Node]:
        """Nodes whose pattern also fits a prefix that is one value longer."""
        out = []
        for n in level:
            if (c := n.children.get(value)) is not None:
                out.append(c)
            if n.star is not None:
                out.append(n.star)
        return out


@dataclass
class Counters:
    candidates: int = 0
    outputs: int = 0
    seeks: int = 0
    seeks_saved: int = 0
    boxes: int = 0
    merges: int = 0
    free_value_calls: int = 0
    complete_hits: int = 0
    cuts: int = 0
    peak_nodes: int = 0

    def row(self) -> dict[str, int]:
        return {f.name: getattr(self, f.name) for f in fields(self)}


class SortedAtom:
    """One relation in the order of the variables, answering for the largest gap around a point."""

    def __init__(self, names: tuple[str, ...], rows: Rows, order: tuple[str, ...]):
        self.places = [order.index(v) for v in names]
        self.trie = Trie(rows)
        self.known: set[tuple] = set()  # prefixes that an interval's end has shown to exist

    def gap_around(self, point: list[int], c: Counters, reuse: bool) -> tuple[tuple, int, int] | None:
        """(pattern, lo, hi) at the first attribute whose prefix is missing; None if the point is in the relation."""
        node, own = self.trie, ()
        for p in self.places:
            value = point[p]
            values = node.values
            if reuse and (*own, value) in self.known:
                c.seeks_saved += 1
                node = node.child(value)
                own = (*own, value)
                continue
            c.seeks += 1
            i = bisect_left(values, value)
            if i < len(values) and values[i] == value:
                node = node.children[i]
                own = (*own, value)
                continue
            lo = values[i - 1] if i else -INF
            hi = values[i] if i < len(values) else INF
            if reuse:
                self.known.update((*own, v) for v in (lo, hi) if abs(v) < INF)
            pattern: list = [None] * p
            for q, v in zip(self.places, own, strict=False):
                pattern[q] = v
            return tuple(pattern), lo, hi
        return None


@dataclass(frozen=True)
class Options:
    frontier: bool = True
    reuse_gap_origin: bool = True
    complete_nodes: bool = True
    cyclic: str = "skeleton"  # or "closure": store the gaps of all atoms


def gap_join(atoms, order: tuple[str, ...], kept: list[int] | None = None, options: Options = Options(), counters: Counters | None = None,
             filters: tuple = (), boxes: list | None = None) -> Iterator[tuple[int, ...]]:
    """All bindings in lexicographic order.

    kept: positions of the atoms whose gaps are stored (a skeleton for which the order is nested);
    gaps of the others only move the frontier. Without them, or with cyclic="closure", all are stored.
    boxes: collects (pattern, lo, hi) of every gap found, the certificate together with the outputs.
    """
    c = counters if counters is not None else Counters()
    ordered = by_order(atoms, order)
    n = len(order)
    rels = [SortedAtom(names, rows, order) for names, rows in ordered]
    stored = set(range(len(rels))) if kept is None or options.cyclic == "closure" else set(kept)
    tree = GapTree()
    low = min((v for _, rows in ordered for r in rows for v in r), default=0)
    high = max((v for _, rows in ordered for r in rows for v in r), default=0)
    point = [low] * n
    levels: list[list[Node]] = [[tree.root]] + [[] for _ in range(n)]
    holds = {"<": int.__lt__, ">": int.__gt__, "<=": int.__le__, ">=": int.__ge__, "!=": int.__ne__}
    checks = [(order.index(a), holds[op], order.index(b)) for a, op, b in filters]

    def relevel(upto: int) -> None:
        for j in range(1, upto + 1):  # inserts may have added or dropped nodes above
            levels[j] = tree.below(levels[j - 1], point[j - 1])

    i = 0
    while i >= 0:
        if i < n:
            x, meet = _free_value(tree, levels[i], i, point, options, c)
            if x > high:
                before = i
                i, whole = _cut(tree, meet, point, i, low, c)
                if i >= 0:
                    _reset(point, i + 1, low)
                    relevel(i)
                    if i < before and whole and not any(m.gaps.covers(point[i]) for m in levels[i]):
                        point[i] += 1  # the box lies where the tree keeps nothing: move by hand
                continue
            if x != point[i]:
                point[i] = x
                _reset(point, i + 1, low)  # deeper coordinates start anew whenever the prefix grows
            levels[i + 1] = tree.below(levels[i], x)
            i += 1
            continue
        c.candidates += 1
        gaps = [(k, g) for k, r in enumerate(rels) if (g := r.gap_around(point, c, options.reuse_gap_origin)) is not None]
        if not gaps:
            if all(op(point[a], point[b]) for a, op, b in checks):
                c.outputs += 1
                yield tuple(point)
            i = n - 1
            if options.frontier:
                point[i] += 1
            else:
                c.boxes += 1
                tree.insert(tuple(point[:-1]), point[-1] - 1, point[-1] + 1)
            relevel(i)
            continue
        back = n - 1
        for k, (pattern, lo, hi) in gaps:
            p = len(pattern)
            if boxes is not None:
                boxes.append((pattern, lo, hi))
            if k in stored:
                c.boxes += 1
                c.merges += tree.insert(pattern, lo, hi)
            back = min(back, p)
            for m in levels[p]:  # a gap that a finished node did not know of: it is not finished
                m.complete, m.passes = False, min(m.passes, 1)
        skipped = [(len(pattern), hi) for k, (pattern, lo, hi) in gaps if k not in stored]
        if skipped and (p := min(s[0] for s in skipped)) <= back:
            # sound for the current prefix only: move on at p, deeper coordinates anew
            hi = max(h for q, h in skipped if q == p)
            point[p] = max(point[p], hi)
            _reset(point, p + 1, low)
        i = back
        relevel(i)
        if not any(m.gaps.covers(point[i]) for m in levels[i]):
            ends = [hi for _, (pattern, lo, hi) in gaps if len(pattern) == i and hi > point[i]]
            if ends:  # the box lies where the tree keeps nothing: move by hand, for this prefix
                point[i] = max(ends)
                _reset(point, i + 1, low)
        c.peak_nodes = max(c.peak_nodes, tree.nodes)


def _reset(point: list[int], k: int, low: int) -> None:
    for j in range(k, len(point)):
        point[j] = low


def _free_value(tree: GapTree, level: list[Node], depth: int, point: list[int], options: Options, c: Counters) -> tuple[int, tuple]:
    """The next value no node of the level covers, going round until all agree, and the meet of their patterns."""
    x = start = point[depth]
    if x >= INF:
        return INF, _meet([m for m in level if m.gaps.lo] or [Node((None,) * depth)], depth)
    active = [m for m in level if m.gaps.lo]
    if not active:
        return x, (None,) * depth
    meet = _meet(active, depth)
    bottom = next((m for m in active if m.pattern == meet), None)
    if options.complete_nodes and bottom is not None and bottom.complete:
        c.complete_hits += 1
        x = bottom.gaps.free_from(x)
        if x < INF:
            return x, meet
    while True:
        before = x
        for m in active:
            c.free_value_calls += 1
            x = m.gaps.free_from(x)
        if x == before:
            break
        if x >= INF:
            x = INF
            break
    if x > start and len(active) > 1:
        node = tree.at(meet)
        if node is not None:
            node.gaps.insert(start - 1, x)  # what was skipped together is remembered at the bottom
            if x >= INF:
                node.passes += 1
                node.complete = node.passes >= 2
            if node not in level:
                level.append(node)
    return x, meet


def _meet(nodes: list[Node], depth: int) -> tuple:
    out: list = [None] * depth
    for m in nodes:
        for k, p in enumerate(m.pattern):
            if p is not None:
                out[k] = p
    return tuple(out)


def _cut(tree: GapTree, meet: tuple, point: list[int], depth: int, low: int, c: Counters) -> tuple[int, bool]:
    """Where to go on after a level ran out: rule out the last value the coverage depends on.

    A box is stored just when the whole line from the smallest value on is covered; where the
    frontier moved over a part of it, the previous coordinate moves by one instead.
    """
    c.cuts += 1
    last = max((k for k, p in enumerate(meet) if p is not None), default=-1)
    node = tree.at(meet, create=False)
    whole = node is not None and node.gaps.free_from(low) >= INF
    if whole:
        if last < 0:
            return -1, True
        tree.insert(meet[:last], meet[last] - 1, meet[last] + 1)
        return last, True
    if depth == 0:
        return -1, False
    point[depth - 1] += 1
    return depth - 1, False


class _PointCounter:
    """Counts over nested elimination orders: a number for every point of a ledger instead of its branches.

    The variables form a tree (a variable hangs on the last earlier one it shares an atom with). A node's
    free points are searched once, for the first prefix that reaches it; the sum of their numbers is then
    multiplied into the point its last constant stands for, which is all that the prefixes after it see.
    """

    def __init__(self, ordered, order: tuple[str, ...], c: Counters):
        self.c, self.tree, self.n = c, GapTree(), len(order)
        self.tries = [Trie(rows) for _, rows in ordered]
        self.uses = [[i for i, (names, _) in enumerate(ordered) if v in names] for v in order]
        self.places = [[order.index(v) for v in names] for names, _ in ordered]
        self.above = [sorted({q for i in self.uses[k] for q in self.places[i] if q < k}) for k in range(self.n)]
        self.below = [[m for m in range(k + 1, self.n) if self.above[m] and self.above[m][-1] == k] for k in range(self.n)]
        self.roots = [k for k in range(self.n) if not self.above[k]]
        self.low = min((v for _, rows in ordered for r in rows for v in r), default=0)
        self.point = [0] * self.n

    def pattern(self, fixed: list[int], depth: int) -> tuple:
        return tuple(self.point[j] if j in fixed else None for j in range(depth))

    def chain(self, k: int) -> list[Node]:
        """Nodes over variable k whose constants the point has, all of them on variables that k meets."""
        level = [self.tree.root]
        for j in range(k):
            level = [x for m in level for x in (m.children.get(self.point[j]) if j in self.above[k] else None, m.star) if x is not None]
        return level

    def solve(self, k: int, at: list[Trie]) -> tuple[Node, dict[int, int] | None]:
        """The finished node of variable k under the point, and the number of each of its points; None if it was finished before."""
        c, pattern = self.c, self.pattern(self.above[k], k)
        node = self.tree.at(pattern) or Node(pattern)
        if node.complete:
            c.complete_hits += 1
            return node, None
        x, live = self.low, []
        while True:
            level, before = [m for m in self.chain(k) if m.gaps.lo], x
            while True:
                turn = x
                for m in level:
                    c.free_value_calls += 1
                    x = m.gaps.free_from(x)
                if x == turn or x >= INF:
                    break
            if x > before and len(level) > 1:
                node.gaps.insert(before - 1, x)
            if x >= INF:
                break
            missing = False
            for i in self.uses[k]:
                c.seeks += 1
                values = at[i].values
                p = bisect_left(values, x)
                if p == len(values) or values[p] != x:
                    missing = True
                    c.boxes += 1
                    own = [q for q in self.places[i] if q < k]
                    c.merges += self.tree.insert(self.pattern(own, k), values[p - 1] if p else -INF, values[p] if p < len(values) else INF)
            if missing:
                continue
            c.candidates += 1
            self.point[k] = x
            if self.branches(k, x, at):
                live.append(x)
            x += 1
        level = self.chain(k)
        numbers = {}
        for x in live:
            number = 1
            for m in level:
                number *= m.counts.get(x, 1)
            numbers[x] = number
        node.complete, node.total = True, sum(numbers.values())
        c.peak_nodes = max(c.peak_nodes, self.tree.nodes)
        return node, numbers

    def branches(self, k: int, x: int, at: list[Trie]) -> bool:
        """Solve what hangs on variable k at x; False, and x is ruled out, if some branch is empty."""
        down = list(at)
        for i in self.uses[k]:
            down[i] = at[i].child(x)
        for m in self.below[k]:
            node, numbers = self.solve(m, down)
            first = self.tree.at(self.pattern([j for j in self.above[m] if j < k], k))  # where the edge labelled x starts
            if not node.total:
                self.c.cuts += 1
                first.gaps.insert(x - 1, x + 1)
                return False
            if numbers is not None:
                first.counts[x] = first.counts.get(x, 1) * node.total
        return True


def gap_counts(atoms, order: tuple[str, ...], counters: Counters | None = None) -> dict[int, int]:
    """value of the first variable -> number of bindings, without listing any; for nested elimination orders."""
    ordered = by_order(atoms, order)
    c = counters if counters is not None else Counters()
    if any(not rows for _, rows in ordered):
        return {}
    counter = _PointCounter(ordered, order, c)
    found: dict[int, int] = {}
    rest = 1
    for r in counter.roots:
        numbers = counter.solve(r, counter.tries)[1]
        if r == 0:
            found = numbers
        else:
            rest *= sum(numbers.values())
    c.outputs += sum(found.values()) * rest
    return {x: n * rest for x, n in found.items()} if rest else {}


def gap_count(atoms, order: tuple[str, ...], counters: Counters | None = None) -> int:
    """The number of bindings: from point counts where the order is nested, else by listing them."""
    from ..query.model import JoinQuery, is_neo

    q = JoinQuery.of(*[("r", *names) for names, _ in atoms])
    if is_neo(q, order):
        return sum(gap_counts(atoms, order, counters).values())
    return sum(1 for _ in gap_join(atoms, order, None, Options(), counters))
