"""Which method evaluates a query, and why."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..operators.acyclic import acyclic_join, hybrid_join, message_count
from ..operators.bind import Relations
from ..operators.pairwise import pairwise_join
from ..operators.prefix import prefix_join
from ..query.bounds import cover_bound
from ..query.model import (JoinQuery, choose_order, elimination_width, is_alpha_acyclic, is_beta_acyclic, skeleton, split_core)


@dataclass(frozen=True)
class PatternPlan:
    query: JoinQuery
    method: str
    reason: str
    order: tuple[str, ...]
    alpha: bool
    beta: bool
    width: int
    bound: float | None
    kept: tuple[int, ...]


def plan_pattern(q: JoinQuery, sizes: dict[str, int] | None = None, mode: str | int = "count") -> PatternPlan:
    alpha, beta = is_alpha_acyclic(q), is_beta_acyclic(q)
    order = choose_order(q)
    tree, core = split_core(q)
    if len(q.atoms) <= 2:
        method, reason = "pairwise", "two atoms: one join is optimal"
    elif alpha and not q.filters:
        method, reason = ("messages", "acyclic count: messages never form output rows") if mode == "count" else (
            "reduce", "acyclic rows: full reduction, then joins without dangling rows")
    elif not alpha and tree and len(core) > 2 and len(core) < len(q.atoms) and not q.filters:
        method, reason = "hybrid", "a tree part hangs on a cyclic core"
    elif all(len(set(a.vars)) <= 2 for a in q.atoms):
        method, reason = "prefix", "cyclic: every step intersects, so no step passes the cover bound"
    else:
        method, reason = "pairwise", "atoms of higher arity outside the acyclic case"
    bound = cover_bound(q, sizes)[0] if sizes else None
    return PatternPlan(q, method, reason, order, alpha, beta, elimination_width(q, order), bound,
                       tuple(skeleton(q, order)[0]))


def evaluate(q: JoinQuery, rels: Relations, mode: str | int = "count", sizes: dict[str, int] | None = None) -> DataFrame:
    method = plan_pattern(q, sizes, mode).method
    if method == "messages":
        return message_count(q, rels, kind="bigint")
    if method == "reduce":
        return acyclic_join(q, rels, mode)
    if method == "hybrid":
        return hybrid_join(q, rels, mode)
    return (prefix_join if method == "prefix" else pairwise_join)(q, rels, mode=mode)


def explain_pattern(q: JoinQuery, rels: Relations, sizes: dict[str, int] | None = None) -> str:
    p = plan_pattern(q, sizes)
    lines = [f"query   {q}", f"method  {p.method}: {p.reason}", f"order   {' '.join(p.order)}",
             f"acyclic alpha={p.alpha} beta={p.beta}, width {p.width}", f"bound   {p.bound}", f"stored  atoms {list(p.kept)}"]
    physical = evaluate(q, rels)._jdf.queryExecution().toString()
    return "\n".join([*lines, physical])


def pattern_sql(q: JoinQuery) -> str:
    """The count of q as portable SQL over relations (src, dst) or (node)."""
    names = {1: ("node",), 2: ("src", "dst")}
    first: dict[str, str] = {}
    conditions = []
    for i, a in enumerate(q.atoms):
        for v, c in zip(a.vars, names[len(a.vars)], strict=True):
            if v in first:
                conditions.append(f"{first[v]} = t{i}.{c}")
            else:
                first[v] = f"t{i}.{c}"
    conditions += [f"{first[a]} {op} {first[b]}" for a, op, b in q.filters]
    tables = ", ".join(f"{a.rel} t{i}" for i, a in enumerate(q.atoms))
    return f"select cast(count(*) as bigint) as cnt from {tables}" + (f" where {' and '.join(conditions)}" if conditions else "")
