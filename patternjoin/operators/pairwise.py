"""Pairwise plans: the comparison baselines, with every join strategy Spark offers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.model import JoinQuery
from .bind import Relations, bind, checkpointed, compare, count_product, finish

STRATEGIES = {"hash": "shuffle_hash", "merge": "merge", "broadcast": "broadcast", "nested_loop": "shuffle_replicate_nl"}


def pairwise_join(q: JoinQuery, rels: Relations, order: list[int] | None = None, strategy: str | None = None,
                  mode: str | int = "count", persist: bool = False) -> DataFrame:
    """Join the atoms one after the other (left-deep), comparisons applied as soon as both ends are bound.

    `order` lists atom positions; by default each next atom shares a variable with the ones before.
    `persist` materialises every intermediate result instead of piping it.
    """
    if mode == "count" and (product := count_product(q, lambda p: pairwise_join(p, rels, None, strategy))) is not None:
        return product
    left = list(order) if order is not None else None
    todo = list(range(len(q.atoms)))
    first = left.pop(0) if left is not None else 0
    todo.remove(first)
    df, bound = bind(q.atoms[first], rels), set(q.atoms[first].vars)
    while todo:
        i = left.pop(0) if left is not None else next((j for j in todo if bound & set(q.atoms[j].vars)), todo[0])
        todo.remove(i)
        atom = q.atoms[i]
        other = bind(atom, rels)
        if strategy:
            other = other.hint(STRATEGIES[strategy])
        shared = [v for v in dict.fromkeys(atom.vars) if v in bound]
        fresh = set(atom.vars) - bound
        df = (df.join(other, shared, "inner" if fresh else "left_semi") if shared else df.crossJoin(other))
        bound |= fresh
        if (c := compare(q, bound, fresh or None)) is not None:
            df = df.where(c)
        if persist:
            df = checkpointed(df)
    return finish(df, mode, q.variables)


def bushy_path(k: int, rels: Relations, mode: str | int = "count") -> DataFrame:
    """Both samples meet their edges first; the two halves meet in the middle."""
    e, half = rels["e"], k // 2
    left = rels["v1"].toDF("x0")
    for i in range(half):
        left = left.join(e.toDF(f"x{i}", f"x{i + 1}"), f"x{i}")
    right = rels["v2"].toDF(f"x{k}")
    for i in range(k, half, -1):
        right = right.join(e.toDF(f"x{i - 1}", f"x{i}"), f"x{i}")
    return finish(left.join(right, f"x{half}"), mode, tuple(f"x{i}" for i in range(k + 1)))


def leftdeep_path(k: int, rels: Relations, mode: str | int = "count") -> DataFrame:
    """One sample, then edge after edge, the other sample last: the large intermediate result."""
    df = rels["v1"].toDF("x0")
    for i in range(k):
        df = df.join(rels["e"].toDF(f"x{i}", f"x{i + 1}"), f"x{i}")
    return finish(df.join(rels["v2"].toDF(f"x{k}"), f"x{k}"), mode, tuple(f"x{i}" for i in range(k + 1)))


def traverse(q: JoinQuery, rels: Relations, start: str, mode: str | int = "count") -> DataFrame:
    """Graph-store traversal: from the atoms of `start`, expand all bindings hop by hop."""
    order, bound = [], {start}
    todo = list(range(len(q.atoms)))
    while todo:
        i = min((j for j in todo if bound & set(q.atoms[j].vars)), key=lambda j: (len(set(q.atoms[j].vars) - bound), j))
        order.append(i)
        todo.remove(i)
        bound |= set(q.atoms[i].vars)
    return pairwise_join(q, rels, order, mode=mode)


def bruteforce(q: JoinQuery, rels: Relations, mode: str | int = "count", most: int = 20) -> DataFrame:
    """All points of the output space against all atoms; for a handful of nodes, as an oracle."""
    domain = None
    for a in q.atoms:
        b = bind(a, rels)
        for v in dict.fromkeys(a.vars):
            one = b.select(F.col(v).alias("x"))
            domain = one if domain is None else domain.union(one)
    domain = domain.distinct()
    if domain.count() > most:
        raise ValueError(f"more than {most} values: brute force is an oracle for small relations")
    df = None
    for v in q.variables:
        one = domain.select(F.col("x").alias(v))
        df = one if df is None else df.crossJoin(one)
    for a in q.atoms:
        df = df.join(bind(a, rels), list(dict.fromkeys(a.vars)), "left_semi")
    if (c := compare(q, set(q.variables))) is not None:
        df = df.where(c)
    return finish(df, mode, q.variables)
