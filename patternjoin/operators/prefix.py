"""Worst-case-optimal join on DataFrames: one variable a step, its candidates intersected.

Every binary relation is held as adjacency lists in the direction a step needs. A step joins the
prefix with the lists of all atoms that bind the next variable and intersects them before
anything is unfolded; the last variable of a count is never unfolded.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.build import adjacency, by_degree
from ..query.model import JoinQuery, choose_order
from .bind import Relations, bind, checkpointed, compare, count_product, finish


def prefix_join(q: JoinQuery, rels: Relations, order: tuple[str, ...] | None = None, mode: str | int = "count",
                by: str | None = None, materialise: tuple[str, str] | None = None, orient: str = "id") -> DataFrame:
    """Count, rows, exists or k rows of q; with `by`, (by, cnt): the count for each value of the first variable.

    `materialise` names a pair of variables: the part of the query that starts with them is
    computed, kept and then used as one atom. `orient="degree"` re-orients an ordered clique by
    degree, which is refused where the order of ids is part of the meaning.
    """
    if orient == "degree":
        return _oriented(q, rels, mode)
    if mode == "count" and by is None and (product := count_product(q, lambda p: prefix_join(p, rels))) is not None:
        return product
    order = order or choose_order(q, cyclic=True)
    if by is not None and order[0] != by:
        raise ValueError("the order has to start with the variable that is counted by")
    lists: dict[tuple, DataFrame] = {}

    def neighbours(atom, key: str, other: str) -> DataFrame:
        name = (atom.rel, atom.vars.index(key))
        if name not in lists:
            lists[name] = adjacency(bind(atom, rels).select(F.col(key).alias("src"), F.col(other).alias("dst"))).toDF("k", "l")
        return lists[name].toDF(key, f"__{key}")

    unary = {v: [a for a in q.atoms if set(a.vars) == {v}] for v in order}
    binary = [a for a in q.atoms if len(set(a.vars)) == 2]
    if any(len(set(a.vars)) > 2 for a in q.atoms):
        raise ValueError("atoms of three or more variables: use hypercube_join")
    v0 = order[0]
    starts = [bind(a, rels).select(v0).distinct() for a in [*unary[v0], *[a for a in binary if v0 in a.vars]]]
    prefix = reduce(lambda x, y: x.join(y, v0, "left_semi"), starts)
    bound = {v0}
    for step, v in enumerate(order[1:], 1):
        last = step == len(order) - 1
        hooks = [(a, next(u for u in a.vars if u != v)) for a in binary if v in a.vars and set(a.vars) - {v} <= bound]
        if not hooks:
            domain = [bind(a, rels).select(v).distinct() for a in q.atoms if v in a.vars]
            prefix = prefix.crossJoin(reduce(lambda x, y: x.join(y, v, "left_semi"), domain))
            bound.add(v)
            continue
        columns = []
        for a, u in hooks:
            prefix = prefix.join(neighbours(a, u, v), u).withColumnRenamed(f"__{u}", f"__l{len(columns)}")
            columns.append(F.col(f"__l{len(columns)}"))
        found = reduce(F.array_intersect, columns)
        for x, op, y in q.filters:
            if {x, y} <= bound | {v} and v in (x, y):
                other, flip = (y, False) if x == v else (x, True)
                found = F.filter(found, _comparison(op, F.col(other), flip))
        if not unary[v] and last and (mode == "count"):
            prefix = prefix.select(*bound, F.size(found).cast("long").alias("__n"))
            return _summed(prefix, by)
        prefix = prefix.select(*bound, F.explode(found).alias(v))
        bound.add(v)
        for a in unary[v]:
            prefix = prefix.join(bind(a, rels), v, "left_semi")
        if materialise and {*materialise} == bound:
            prefix = checkpointed(prefix)
    if mode == "count":
        return _summed(prefix.withColumn("__n", F.lit(1).cast("long")), by)
    return finish(prefix, mode, q.variables)


def probing_join(q: JoinQuery, rels: Relations, order: tuple[str, ...] | None = None, mode: str | int = "count") -> DataFrame:
    """Prefix extension without lists, for graphs with hubs: no row ever holds a node's neighbours.

    For the next variable every prefix takes the atom with the fewest candidates, by counted degrees; its
    edges are joined and the other atoms probed by semijoins on the whole edge, whose keys no hub can heat.
    So a step makes no more rows than its smallest list has, which is the bound of the prefix form.
    """
    if mode == "count" and (product := count_product(q, lambda p: probing_join(p, rels))) is not None:
        return product
    order = order or choose_order(q, cyclic=True)
    if any(len(set(a.vars)) > 2 for a in q.atoms):
        raise ValueError("atoms of three or more variables: use hypercube_join")
    v0 = order[0]
    prefix = reduce(lambda x, y: x.join(y, v0, "left_semi"), [bind(a, rels).select(v0).distinct() for a in q.atoms if v0 in a.vars])
    bound = {v0}
    for v in order[1:]:
        hooks = [(a, next(u for u in a.vars if u != v)) for a in q.atoms if len(set(a.vars)) == 2 and v in a.vars and set(a.vars) - {v} <= bound]
        if not hooks:
            raise ValueError(f"{v} meets no earlier variable in this order")
        edges = [bind(a, rels).select(u, v) for a, u in hooks]
        for i, (_, u) in enumerate(hooks if len(hooks) > 1 else []):
            prefix = prefix.join(edges[i].groupBy(u).agg(F.count("*").alias(f"__d{i}")), u)
        fewest = F.least(*[F.col(f"__d{i}") for i in range(len(hooks))]) if len(hooks) > 1 else None
        branches = []
        for i, (_, u) in enumerate(hooks):
            own = prefix
            if fewest is not None:  # ties go to the first atom
                own = own.where(reduce(lambda x, y: x & y, [F.col(f"__d{i}") == fewest, *[F.col(f"__d{j}") > fewest for j in range(i)]]))
            own = own.join(edges[i], u)
            for j, (_, w) in enumerate(hooks):
                if j != i:
                    own = own.join(edges[j], [w, v], "left_semi")
            branches.append(own.select(*[x for x in order if x in bound or x == v]))
        bound.add(v)
        prefix = reduce(lambda x, y: x.unionByName(y), branches)
        for a in q.atoms:
            if set(a.vars) == {v}:
                prefix = prefix.join(bind(a, rels), v, "left_semi")
        if (c := compare(q, bound, {v})) is not None:
            prefix = prefix.where(c)
    return finish(prefix, mode, q.variables)


def _comparison(op: str, other, flip: bool):
    def holds(x):
        a, b = (other, x) if flip else (x, other)
        return {"<": a < b, ">": a > b, "<=": a <= b, ">=": a >= b, "!=": a != b}[op]

    return holds


def _summed(df: DataFrame, by: str | None) -> DataFrame:
    total = F.coalesce(F.sum("__n"), F.lit(0)).cast("long").alias("cnt")
    return df.groupBy(by).agg(total) if by else df.agg(total)


def _oriented(q: JoinQuery, rels: Relations, mode: str | int) -> DataFrame:
    """A clique over one relation has one count whatever total order its nodes are put in."""
    names = {a.rel for a in q.atoms}
    n = len(q.variables)
    pairs = {frozenset(a.vars) for a in q.atoms}
    if len(names) != 1 or len(pairs) != n * (n - 1) // 2 or len(q.atoms) != len(pairs) or not q.filters:
        raise ValueError("only an ordered clique may be re-oriented: elsewhere the order of ids is part of the meaning")
    name = names.pop()
    bare = JoinQuery(q.atoms)  # arcs already point up the degree order, so no comparison is left
    out = prefix_join(bare, {name: by_degree(rels[name])}, q.variables, mode)
    if mode in ("count", "exists"):
        return out
    ids = F.array_sort(F.array(*q.variables))
    return out.select(*[ids[i].alias(v) for i, v in enumerate(q.variables)])


def triangles_by_node(edges: DataFrame) -> DataFrame:
    """(node, triangles) over all corners, from arcs that point up the degree order."""
    arcs = by_degree(edges)
    lists = adjacency(arcs)
    third = F.array_intersect("l1", "l2")
    t = (arcs.join(lists.toDF("src", "l1"), "src").join(lists.toDF("dst", "l2"), "dst")
         .select("src", "dst", F.explode(third).alias("w")))
    return t.select(F.explode(F.array("src", "dst", "w")).alias("node")).groupBy("node").agg(F.count("*").alias("triangles"))


def gas_triangles(edges: DataFrame) -> DataFrame:
    """Gather neighbour sets, intersect them along every edge, scatter the counts (each triangle from its three edges)."""
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    sets = adjacency(both)
    per_edge = edges.join(sets.toDF("src", "a"), "src").join(sets.toDF("dst", "b"), "dst").select(
        F.size(F.array_intersect("a", "b")).cast("long").alias("n"))
    return per_edge.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select(F.expr("n div 3").alias("cnt"))


def gas_cliques4(edges: DataFrame) -> DataFrame:
    """Triangles keep their shared neighbour sets, which are intersected a second time."""
    up = adjacency(edges)
    t = (edges.join(up.toDF("src", "a"), "src").join(up.toDF("dst", "b"), "dst")
         .select(F.array_intersect("a", "b").alias("c")).select("c", F.explode("c").alias("w")))
    return t.join(up.toDF("w", "l"), "w").agg(
        F.coalesce(F.sum(F.size(F.array_intersect("c", "l"))), F.lit(0)).cast("long").alias("cnt"))


def heavy_light_triangles(edges: DataFrame, threshold: int | None = None) -> DataFrame:
    """Triangles with a light corner from its wedges, triangles of heavy corners only from their own small graph."""
    from ..graph.build import degrees, symmetric

    if threshold is None:
        threshold = max(1, int(edges.count() ** 0.5))
    d = degrees(edges)
    heavy = d.where(F.col("degree") > threshold).select("node")
    sym = symmetric(edges)
    tagged = edges.join(heavy.select(F.col("node").alias("src"), F.lit(1).alias("hs")), "src", "left").join(
        heavy.select(F.col("node").alias("dst"), F.lit(1).alias("hd")), "dst", "left")
    core = tagged.where("hs = 1 and hd = 1").select("src", "dst")
    in_core = prefix_join(JoinQuery.of(("e", "a", "b"), ("e", "b", "c"), ("e", "a", "c")), {"e": core}).select("cnt")
    # a wedge belongs to the smallest light corner of its triangle
    light = sym.join(heavy.toDF("src"), "src", "left_anti")
    a, b = light.toDF("m", "x"), light.toDF("m", "y")
    wedge = a.join(b, "m").where("x < y").join(edges.toDF("x", "y"), ["x", "y"], "left_semi")
    hx, hy = heavy.select(F.col("node").alias("x"), F.lit(1).alias("hx")), heavy.select(F.col("node").alias("y"), F.lit(1).alias("hy"))
    first = wedge.join(hx, "x", "left").join(hy, "y", "left").where("(hx = 1 or m < x) and (hy = 1 or m < y)")
    return in_core.unionByName(first.agg(F.count("*").alias("cnt"))).agg(F.sum("cnt").cast("long").alias("cnt"))


def cycles4_by_wedges(edges: DataFrame) -> DataFrame:
    """All squares: pairs of wedges over the same two opposite corners, each square seen from both diagonals."""
    from ..graph.build import symmetric

    s = symmetric(edges)
    k = s.toDF("m", "x").join(s.toDF("m", "y"), "m").where("x < y").groupBy("x", "y").agg(F.count("*").alias("k"))
    return k.agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).alias("n")).select(F.expr("n div 2").alias("cnt"))
