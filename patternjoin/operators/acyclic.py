"""Acyclic queries: semijoin reduction, count messages, and the hybrid with a cyclic core."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.model import JoinQuery, elimination_depth, join_tree, nested_elimination_orders, split_core
from .bind import Relations, bind, checkpointed, count_product, finish
from .prefix import prefix_join


def _rooted(q: JoinQuery, root_var: str | None) -> list[tuple[int, int | None]]:
    """The join tree as (atom, parent), leaves first, hung up at an atom that holds root_var."""
    tree = join_tree(q)
    if tree is None:
        raise ValueError("the query is cyclic")
    near: dict[int, set[int]] = {i: set() for i in range(len(q.atoms))}
    for i, p in tree:
        if p is not None:
            near[i].add(p)
            near[p].add(i)
    root = next(i for i in range(len(q.atoms)) if root_var is None or root_var in q.atoms[i].vars) if root_var else tree[-1][0]
    out, stack = [], [(root, None)]
    while stack:
        i, p = stack.pop()
        out.append((i, p))
        stack += [(j, i) for j in near[i] if j != p]
    return out[::-1]


def _messages(q: JoinQuery, rels: Relations, root_var: str | None, kind: str) -> tuple[DataFrame, int]:
    """Counts of the root atom's rows, everything below summed up edge by edge of the join tree."""
    tree = _rooted(q, root_var)
    held = {i: bind(a, rels) for i, a in enumerate(q.atoms)}
    weighted: set[int] = set()
    for i, parent in tree[:-1]:
        shared = [v for v in dict.fromkeys(q.atoms[i].vars) if v in q.atoms[parent].vars]
        own = held[i]
        if i not in weighted and set(shared) == set(q.atoms[i].vars):
            held[parent] = held[parent].join(own, shared, "left_semi")  # a plain sample: nothing to add up
            continue
        w = F.sum("__w") if i in weighted else F.count("*")
        message = own.groupBy(*shared).agg(w.cast(kind).alias("__m"))
        up = held[parent].join(message, shared) if shared else held[parent].crossJoin(message)
        product = (F.col("__w") * F.col("__m")).cast(kind) if parent in weighted else F.col("__m")
        held[parent] = up.withColumn("__w", product).drop("__m")
        weighted.add(parent)
    root = tree[-1][0]
    df = held[root] if root in weighted else held[root].withColumn("__w", F.lit(1).cast(kind))
    return df, root


def message_count(q: JoinQuery, rels: Relations, root: str | None = None, kind: str = "decimal(38,0)") -> DataFrame:
    """The count of an acyclic query by messages from the leaves to the root: no output row is ever formed.

    Counts are DECIMAL(38,0) unless `kind` says bigint, which overflows with an error and never silently.
    """
    if q.filters:
        raise ValueError("comparisons between atoms cannot be counted by messages")
    if (product := count_product(q, lambda p: message_count(p, rels, None, kind))) is not None:
        return product
    df, _ = _messages(q, rels, root, kind)
    return df.agg(F.coalesce(F.sum("__w"), F.lit(0)).cast(kind).alias("cnt"))


def message_to(q: JoinQuery, rels: Relations, variable: str, kind: str = "decimal(38,0)") -> DataFrame:
    """(variable, w): how many bindings of q end in each value of one variable."""
    df, _ = _messages(q, rels, variable, kind)
    return df.groupBy(variable).agg(F.sum("__w").cast(kind).alias("w"))


#: Bits of a Bloom filter: one for this many keys at least, at most this many in all, and hashes of a key.
BLOOM_BITS_A_KEY, BLOOM_MOST_BITS, BLOOM_HASHES = 10, 1 << 24, 3


def _bloom_places(columns: list[str], bits: int):
    return [F.pmod(F.xxhash64(*columns, F.lit(k)), F.lit(bits)) for k in range(BLOOM_HASHES)]


def bloom_words(keys: DataFrame, bits: int) -> DataFrame:
    """One row, one array with all words of the filter: bits are set by aggregation, no key is gathered."""
    marked = keys.select(F.explode(F.array(*_bloom_places(keys.columns, bits))).alias("p")).select(
        F.shiftright("p", 6).alias("at"), F.expr("shiftleft(1L, cast(p & 63 as int))").alias("word"))
    every = keys.sparkSession.range(bits // 64).select(F.col("id").alias("at"), F.lit(0).cast("long").alias("word"))
    words = marked.unionByName(every).groupBy("at").agg(F.bit_or("word").alias("word"))
    return words.agg(F.array_sort(F.collect_list(F.struct("at", "word"))).getField("word").alias("bloom"))


def bloom_reduce(df: DataFrame, keys: DataFrame) -> DataFrame:
    """Rows of df that may have a partner among keys (same column names); keys too many for a filter leave df as it is.

    The filter is a scalar subquery, so it is tested where df is scanned, before any exchange.
    """
    bits = 1 << 12
    need = BLOOM_BITS_A_KEY * keys.count()
    if need > BLOOM_MOST_BITS:
        return df
    while bits < need:
        bits *= 2
    words = bloom_words(keys, bits).scalar()
    hit = None
    for p in _bloom_places(keys.columns, bits):
        word = words[F.shiftright(p, 6).cast("int")]
        one = F.call_function("shiftright", word, p.bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1)) == 1
        hit = one if hit is None else hit & one
    return df.where(hit)


def full_reduce(q: JoinQuery, rels: Relations, bloom: bool = False) -> dict[int, DataFrame]:
    """Atoms without dangling rows: semijoins up the tree, then down.

    With `bloom` every semijoin of the first pass is preceded by a Bloom filter over the smaller side's keys.
    """
    tree = _rooted(q, None)
    held = {i: bind(a, rels) for i, a in enumerate(q.atoms)}

    def reduced(a: int, b: int, ahead: bool) -> DataFrame:
        shared = [v for v in dict.fromkeys(q.atoms[a].vars) if v in q.atoms[b].vars]
        if not shared:
            return held[a]
        keys = held[b].select(*shared).distinct()
        if not ahead:
            return held[a].join(keys, shared, "left_semi")
        keys = checkpointed(keys)  # read twice: by the filter and by the semijoin
        return bloom_reduce(held[a], keys).join(keys, shared, "left_semi")

    for i, parent in tree[:-1]:
        held[parent] = reduced(parent, i, bloom)
    for i, parent in reversed(tree[:-1]):
        held[i] = reduced(i, parent, False)
    return held


def acyclic_join(q: JoinQuery, rels: Relations, mode: str | int = "count", bloom: bool = False) -> DataFrame:
    """Reduce fully, then join from the root to the leaves: no intermediate row is lost later."""
    held = full_reduce(q, rels, bloom)
    tree = _rooted(q, None)[::-1]
    df, bound = held[tree[0][0]], set(q.atoms[tree[0][0]].vars)
    for i, _ in tree[1:]:
        own = list(dict.fromkeys(q.atoms[i].vars))
        shared = [v for v in own if v in bound]
        df = df.join(held[i], shared, "inner" if set(own) - bound else "left_semi") if shared else df.crossJoin(held[i])
        bound |= set(own)
    for a, op, b in q.filters:
        df = df.where(F.expr(f"`{a}` {op} `{b}`"))
    return finish(df, mode, q.variables)


def hybrid_join(q: JoinQuery, rels: Relations, mode: str | int = "count", path: str = "messages") -> DataFrame:
    """Tree part by messages (or reduction), cyclic core by prefix extension, met on the shared variable.

    The core is only evaluated around values that the tree part reaches. path="gapbox" counts the tree part
    with the gap-box join's numbers for points. Counts are DECIMAL(38,0).
    """
    tree, core = split_core(q)
    if not tree or not core or len(core) == len(q.atoms):
        raise ValueError("the query has no tree part beside a cyclic core")
    t = JoinQuery(tuple(q.atoms[i] for i in sorted(tree)))
    c = JoinQuery(tuple(q.atoms[i] for i in core), tuple(f for f in q.filters))
    shared = [v for v in c.variables if v in t.variables]
    if len(shared) != 1:
        raise ValueError("tree and core have to meet in one variable")
    x = shared[0]
    order = (x, *[v for v in c.variables if v != x])
    weights = _weights(t, rels, x, path)
    around = JoinQuery((*c.atoms, *JoinQuery.of(("__reached", x)).atoms), c.filters)
    inner = rels | {"__reached": weights.select(x)}
    if mode == "count":
        k = prefix_join(around, inner, order, by=x).select(x, F.col("cnt").cast("decimal(38,0)").alias("cnt"))
        return k.join(weights, x).agg(F.coalesce(F.sum((F.col("cnt") * F.col("w")).cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("cnt"))
    rows = prefix_join(around, inner, order, mode="rows")
    return finish(rows.join(acyclic_join(t, rels, "rows"), x), mode, q.variables)


def _weights(t: JoinQuery, rels: Relations, x: str, path: str) -> DataFrame:
    if path == "messages":
        return message_to(t, rels, x)
    from .cells import partitioned_gap_join

    order = max((o for o in nested_elimination_orders(t) if o[0] == x), key=lambda o: elimination_depth(t, o))
    return partitioned_gap_join(t, rels, parts=4, order=order, mode="by", points=True)


def decompose(df: DataFrame, key: str) -> dict[str, DataFrame]:
    """One (key, attribute) relation for each column: nulls are simply absent."""
    return {c: df.where(F.col(c).isNotNull()).select(key, c) for c in df.columns if c != key}


def recompose(parts: dict[str, DataFrame], key: str, where: dict[str, str] | None = None) -> DataFrame:
    """Rows whose attributes all exist, each part filtered before the join on the key."""
    kept = [p.where((where or {}).get(c, "true")) for c, p in parts.items()]
    return reduce(lambda a, b: a.join(b, key), kept)


def delta_count(q: JoinQuery, base: DataFrame, delta: DataFrame, rel: str = "e", others: Relations | None = None) -> DataFrame:
    """How many results appear when the rows of delta join base: one term for each atom of `rel`.

    In term i, atoms before i read the new version, atom i the really new rows, atoms after i the old
    version. Rows that base has already add nothing.
    """
    base = base.distinct()
    new = delta.distinct().join(base, base.columns, "left_anti")
    after = base.unionByName(new)
    places = [i for i, a in enumerate(q.atoms) if a.rel == rel]
    terms = []
    for p in places:
        named = [(f"__{'new' if i == p else 'after' if i < p else 'before'}" if a.rel == rel else a.rel, *a.vars) for i, a in enumerate(q.atoms)]
        term = JoinQuery.of(*[named[p], *named[:p], *named[p + 1:]], filters=q.filters)
        order = [v for v in q.atoms[p].vars]
        rest = tuple(v for v in q.variables if v not in order)
        terms.append(prefix_join(term, (others or {}) | {"__new": new, "__after": after, "__before": base}, (*order, *rest)))
    return reduce(lambda a, b: a.unionByName(b), terms).agg(F.sum("cnt").cast("long").alias("cnt"))
