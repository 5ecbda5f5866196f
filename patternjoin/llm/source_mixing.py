"""Mixing sources to target weights with a min-cost flow.

Documents are aggregated by membership pattern (the set of sources they belong to). Token
capacity flows from patterns to source quotas; the first use of a pattern's tokens costs
nothing and each repetition costs more, so nothing is repeated before all else is used once.
The flow of a pattern is then filled with whole documents in a seeded order.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD

#: Patterns the driver's flow network may have; more is an error and not a silent cut.
MAX_PATTERNS = 100_000
#: Hex digits of the seeded key that name a bucket, level by level: at most 256 sums below each.
BUCKET_DIGITS = (2, 4)


def capped_targets(sizes: Sequence[float], weights: Sequence[float], cap: float) -> list[float]:
    """Share sum(sizes) by weight, none above cap * size, the excess shared again by weight."""
    order = sorted(range(len(sizes)), key=lambda i: cap * sizes[i] / weights[i])
    left, weight = float(sum(sizes)), float(sum(weights))
    targets = [0.0] * len(sizes)
    for place, i in enumerate(order):
        level = left / weight
        if cap * sizes[i] > level * weights[i]:
            for j in order[place:]:
                targets[j] = level * weights[j]
            break
        targets[i] = float(cap * sizes[i])
        left -= targets[i]
        weight -= weights[i]
    return targets


def min_cost_flow(capacity: dict[str, float], members: dict[str, Sequence[str]], quota: dict[str, float],
                  repeats: int) -> dict[tuple[str, str], float]:
    """Flow (pattern, source) -> tokens of least cost among those that meet the quotas as far as capacity allows.

    Layer r of a pattern (its tokens used for the r-th time) costs r - 1 a token. Only the arcs from
    the origin cost anything and a path uses one of them, so the cheapest paths are those over the
    lowest layer that is open: a maximum flow, extended layer by layer, is the min-cost flow.
    """
    patterns, sources = list(capacity), list(quota)
    place = {s: len(patterns) + i for i, s in enumerate(sources)}
    origin, end = len(patterns) + len(sources), len(patterns) + len(sources) + 1
    room: list[dict[int, float]] = [{} for _ in range(end + 1)]

    def arc(a: int, b: int, most: float) -> None:
        room[a][b] = room[a].get(b, 0.0) + most
        room[b].setdefault(a, 0.0)

    for i, p in enumerate(patterns):
        for s in members[p]:
            arc(i, place[s], float("inf"))
    for s, q in quota.items():
        arc(place[s], end, q)
    tiny = 1e-9 * max(1.0, sum(quota.values()))
    for _ in range(repeats):
        for i, p in enumerate(patterns):
            arc(origin, i, capacity[p])
        _extend(room, origin, end, tiny)
    return {(p, s): used for i, p in enumerate(patterns) for s in members[p] if (used := room[place[s]][i]) > tiny}


def _extend(room: list[dict[int, float]], origin: int, end: int, tiny: float) -> None:
    """Blocking flows along shortest paths until none is left."""
    while True:
        level = {origin: 0}
        queue = deque([origin])
        while queue:
            a = queue.popleft()
            for b, r in room[a].items():
                if r > tiny and b not in level:
                    level[b] = level[a] + 1
                    queue.append(b)
        if end not in level:
            return
        left = {a: iter(list(room[a])) for a in level}
        ahead = {a: next(left[a], None) for a in level}
        path = [origin]
        while path:
            a = path[-1]
            if a == end:
                push = min(room[x][y] for x, y in zip(path, path[1:], strict=False))
                for x, y in zip(path, path[1:], strict=False):
                    room[x][y] -= push
                    room[y][x] += push
                # go on from the first arc that is full now
                path = path[:1 + next(i for i, (x, y) in enumerate(zip(path, path[1:], strict=False)) if room[x][y] <= tiny)]
                continue
            b = ahead[a]
            if b is None:
                path.pop()
                if path:
                    ahead[path[-1]] = next(left[path[-1]], None)
            elif level.get(b) == level[a] + 1 and room[a][b] > tiny:
                path.append(b)
            else:
                ahead[a] = next(left[a], None)


def mix_sources(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: int = 3, seed: str = "mix",
                id_column: str = "doc_id", text_column: str = "text", source_column: str = "source") -> DataFrame:
    """(doc_id, size, source_size, target, taken, uses), one row for each input row.

    `source` may be a string, or an array of strings for documents of several sources (target and
    source_size are then those of the whole pattern). Sources sort by code point, null last, and
    take `weights` in turn. Null texts have size 0 and are never taken. Rows are told apart by the
    seeded digest of their id; repeated rows share a digest and fall on the same side except at
    the boundary. An empty table gives no rows; extra columns are not read.
    """
    kind = docs.schema[source_column].dataType.typeName()
    size = F.coalesce(F.regexp_count(F.col(text_column).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")
    source = F.col(source_column)
    if kind == "array":
        pattern = F.to_json(F.array_sort(F.array_distinct(F.transform(
            F.when(F.size(source) > 0, source).otherwise(F.array(F.lit(None).cast("string"))),
            lambda s: F.when(s.isNull(), F.lit("0")).otherwise(F.concat(F.lit("1"), s))))))
    else:
        pattern = F.to_json(F.array(F.when(source.isNull(), F.lit("0")).otherwise(
            F.concat(F.lit("1"), source.cast("string")))))
    key = F.md5(F.concat(F.lit(f"{seed}/"), F.coalesce(F.col(id_column).cast("string"), F.lit(""))))
    sized = docs.select(F.col(id_column).alias("doc_id"), size.alias("size"), pattern.alias("pattern"), key.alias("key"))
    return _fill(sized, weights, cap)


def _fill(sized: DataFrame, weights: Sequence[float], cap: int) -> DataFrame:
    import json

    from .common import cut

    spark = sized.sparkSession
    sized = cut(sized, "mix-sizes")
    rows = sized.groupBy("pattern").agg(F.sum("size").alias("n")).limit(MAX_PATTERNS + 1).collect()
    if len(rows) > MAX_PATTERNS:
        raise ValueError(f"more than {MAX_PATTERNS} membership patterns; coarsen the sources")
    capacity = {r["pattern"]: float(r["n"]) for r in rows}
    members = {p: json.loads(p) for p in capacity}
    held: dict[str, float] = {}
    for p, c in capacity.items():
        for s in members[p]:
            held[s] = held.get(s, 0.0) + c / len(members[p])  # tokens of several sources count in equal parts
    names = sorted(held, key=lambda s: (s[0] == "0", s))
    cycle = [float(weights[i % len(weights)]) for i in range(len(names))]
    quota = dict(zip(names, capped_targets([held[s] for s in names], cycle, cap), strict=True))
    flow = min_cost_flow(capacity, members, quota, cap)
    all_given = dict.fromkeys(capacity, 0.0)
    for (p, _), v in flow.items():
        all_given[p] += v
    plan = []
    for p, c in capacity.items():
        given = all_given[p]
        if len(members[p]) == 1 and abs(given - quota[members[p][0]]) <= 1e-6 * max(1.0, given):
            given = quota[members[p][0]]  # the whole quota: without the flow's rounding
        full = min(cap, int(given // c)) if c else 0
        plan.append((p, int(c), given, full, given - full * c if full < cap else 0.0))
    plan_df = spark.createDataFrame(plan, "pattern string, source_size long, target double, full int, rest double")
    # running totals level by level: over the coarse buckets of a pattern, the fine ones of each, the rows of each
    names = [f"b{n}" for n in BUCKET_DIGITS]
    bucketed = sized.select("*", *[F.substring("key", 1, n).alias(c) for c, n in zip(names, BUCKET_DIGITS, strict=True)])
    fine = bucketed.groupBy("pattern", *names).agg(F.sum("size").alias("n"))
    before = None
    for k, name in enumerate(names):
        sums = fine.groupBy("pattern", *names[:k + 1]).agg(F.sum("n").alias("n"))
        order = Window.partitionBy("pattern", *names[:k]).orderBy(name).rowsBetween(Window.unboundedPreceding, -1)
        own = sums.select("pattern", *names[:k + 1], F.coalesce(F.sum("n").over(order), F.lit(0)).alias(f"s{k}"))
        before = own if before is None else own.join(before, ["pattern", *names[:k]]).withColumn(f"s{k}", F.col(f"s{k}") + F.col(f"s{k - 1}")).drop(f"s{k - 1}")
    inside = Window.partitionBy("pattern", *names).orderBy("key", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    placed = (bucketed.join(before, ["pattern", *names])
              .withColumn("cum", F.col(f"s{len(names) - 1}") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
              .join(F.broadcast(plan_df), "pattern"))  # at most MAX_PATTERNS rows
    extra = ((F.col("full") < cap) & (2 * F.col("cum") + F.col("size") <= 2 * F.col("rest"))).cast("int")
    uses = F.when(F.col("size") > 0, F.col("full") + extra).otherwise(F.lit(0))
    return placed.select("doc_id", "size", "source_size", "target", (uses * F.col("size")).cast("long").alias("taken"),
                         uses.alias("uses"))
