"""Atoms as DataFrames whose columns are the query's variables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.model import Atom, JoinQuery

Relations = dict[str, DataFrame]


def bind(atom: Atom, rels: Relations) -> DataFrame:
    """The atom's relation without nulls; a repeated variable keeps the rows where both agree.

    Relations are sets: the graph builders return distinct rows, other callers see to it once.
    """
    df = rels[atom.rel]
    if len(df.columns) != len(atom.vars):
        raise ValueError(f"{atom.rel} has {len(df.columns)} columns, the atom {len(atom.vars)} variables")
    names = [f"_{i}" for i in range(len(atom.vars))]
    df = df.toDF(*names)
    for i, v in enumerate(atom.vars):
        j = atom.vars.index(v)
        df = df.where(F.col(names[i]) == F.col(names[j])) if j < i else df.where(F.col(names[i]).isNotNull())
    return df.select(*[F.col(names[atom.vars.index(v)]).alias(v) for v in dict.fromkeys(atom.vars)])


def checkpointed(df: DataFrame) -> DataFrame:
    """A kept intermediate result, in the shared checkpoint folder: nothing stays in executors' memory.

    Where no folder is set (a session of one machine) it is persisted instead.
    """
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None:
            return df.persist()
        spark.sparkContext.setCheckpointDir(named)
    return df.checkpoint(eager=False)


def compare(q: JoinQuery, bound: set[str], fresh: set[str] | None = None):
    """The conditions whose variables are all bound (and touch a fresh one), as a Column or None."""
    ready = [F.expr(f"`{a}` {op} `{b}`") for a, op, b in q.filters
             if {a, b} <= bound and (fresh is None or fresh & {a, b})]
    return reduce(lambda x, y: x & y, ready) if ready else None


def finish(df: DataFrame, mode: str | int, variables: tuple[str, ...]) -> DataFrame:
    """count: one row `cnt`; exists: one row `found`; rows: all bindings; a number: that many of them."""
    if mode == "count":
        return df.agg(F.count("*").alias("cnt"))
    if mode == "exists":
        return df.limit(1).agg((F.count("*") > 0).alias("found"))
    return df.select(*variables) if mode == "rows" else df.select(*variables).limit(int(mode))


def components(q: JoinQuery) -> list[JoinQuery]:
    """Parts of the query that share no variable."""
    left, out = list(q.atoms), []
    while left:
        part, seen = [left.pop(0)], set()
        seen |= set(part[0].vars)
        grown = True
        while grown:
            grown = [a for a in left if seen & set(a.vars) or any({x, y} & seen and {x, y} & set(a.vars) for x, _, y in q.filters)]
            for a in grown:
                left.remove(a)
                part.append(a)
                seen |= set(a.vars)
        out.append(JoinQuery(tuple(part), tuple(f for f in q.filters if {f[0], f[2]} <= seen)))
    return out


def count_product(q: JoinQuery, one) -> DataFrame | None:
    """Unrelated parts multiply their counts; no product of rows is formed."""
    parts = components(q)
    if len(parts) == 1:
        return None
    total = None
    for i, p in enumerate(parts):
        n = one(p).select(F.lit(1).alias("k"), F.col("cnt").cast("bigint").alias(f"c{i}"))
        total = n if total is None else total.join(n, "k")
    return total.select(reduce(lambda x, y: x * y, [F.col(f"c{i}") for i in range(len(parts))]).alias("cnt"))
