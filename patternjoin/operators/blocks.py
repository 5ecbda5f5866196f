"""Cliques and squares counted over packed blocks of a graph: no wedge is ever written.

Nodes are hashed to groups; the arcs between two groups are a few packed arrays (about 2 bytes an arc).
A cell is a choice of groups, one for each corner that is cut, and gets every block it needs once. In
a cell the joins run node by node over flat lists, so intermediate rows live for one node only.
"""

from __future__ import annotations

from decimal import Decimal
from functools import reduce
from itertools import combinations, combinations_with_replacement, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.build import _pairs
from ..kernel.intersect import sorted_set
from ..streaming.views import folder
from .recursive import written

#: Groups of the packed blocks, and pieces of a block by its first node: a piece is packed in one go.
GROUPS, PIECES = 12, 8
#: Arcs a cell may hold, at 8 bytes each while they are sorted and 4 after.
CELL_ARCS = 25_000_000
#: Lines that may be hubs (63 to a word of a mask) and the classes a hub has at least; types of classes, and those of a block.
HUBS, HUB_CLASSES, TYPES, TYPE_BLOCK = 126, 16, 20_000, 512


def _planes(x: np.ndarray) -> bytes:
    return np.ascontiguousarray(x.astype("<i8").view(np.uint8).reshape(-1, 8).T).tobytes()


def _numbers(raw: memoryview, n: int) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8, 8 * n).reshape(8, n).T).view("<i8").ravel()


def pack(src: np.ndarray, dst: np.ndarray) -> tuple[int, bytes]:
    """Number of different arcs and their bytes: differences along the sorted arcs, byte plane by byte plane."""
    if min(src.min(), dst.min()) >= 0 and max(src.max(), dst.max()) < 1 << 31:
        key = sorted_set(src << 32 | dst)
        src, dst = key >> 32, key & 0xFFFFFFFF
    else:
        at = np.lexsort((dst, src))
        src, dst = src[at], dst[at]
        new = np.ones(len(src), bool)
        new[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
        src, dst = src[new], dst[new]
    begin = np.flatnonzero(np.diff(src, prepend=src[0] - 1))
    far = np.diff(dst, prepend=0)
    far[begin] = dst[begin] - src[begin]
    own = src[begin]
    raw = _planes(np.diff(own, prepend=0)) + _planes(np.diff(np.append(begin, len(src)))) + _planes(far)
    return len(src), np.array([len(begin), len(src), len(raw)], "<i8").tobytes() + pa.compress(raw, "zstd", asbytes=True)


def unpack(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first nodes, arcs of each, second nodes)."""
    m, n, size = np.frombuffer(data, "<i8", 3).tolist()
    raw = memoryview(pa.decompress(data[24:], size, "zstd", asbytes=True))
    own, many, far = np.cumsum(_numbers(raw, m)), _numbers(raw[8 * m:], m), _numbers(raw[16 * m:], n)
    begin = np.cumsum(many) - many
    total = np.cumsum(far)
    before = total[begin] - far[begin]
    return own, many, total - np.repeat(before - own, many)


def packed_blocks(arcs: DataFrame, weights: DataFrame | None = None, groups: int = GROUPS, pieces: int = PIECES) -> DataFrame:
    """(a, b, n, data): the different arcs (src, dst) from group a to group b, kept in the shared folder.

    Weights (node, w) are blocks to a group -1, with n = 0.
    """
    place = lambda v: F.pmod(F.xxhash64(v), F.lit(groups))
    piece = (place("src") * groups + place("dst")) * pieces + F.pmod(F.xxhash64("src", F.lit(1)), F.lit(pieces))

    def run(key: tuple[pa.Scalar, ...], part: pa.Table) -> pa.Table:
        n, data = pack(part["src"].to_numpy(), part["dst"].to_numpy())
        block = key[0].as_py() // pieces
        a, b = (block // groups, block % groups) if block >= 0 else (-1 - block, -1)
        return pa.table({"a": [a], "b": [b], "n": [n if b >= 0 else 0], "data": pa.array([data], pa.binary())})

    rows = arcs.select(piece.cast("int").alias("piece"), F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    if weights is not None:
        rows = rows.unionByName(weights.select((-(place("node") + 1) * pieces).cast("int").alias("piece"), F.col("node").cast("long").alias("src"),
                                               F.col("w").cast("long").alias("dst")))
    blocks = rows.groupBy("piece").applyInArrow(run, "a long, b long, n long, data binary")
    return written(blocks, folder(arcs.sparkSession, "blocks"))


def _dealt(blocks: DataFrame, groups: int, needs: dict[int, set[tuple[int, int]]]) -> DataFrame:
    """Each block to every cell that needs it, blocks of the fine groups by those of the cells."""
    to: dict[tuple[int, int], list[int]] = {}
    for cell, wanted in needs.items():
        for block in wanted:
            to.setdefault(block, []).append(cell)
    at = blocks.sparkSession.createDataFrame([(a, b, cells) for (a, b), cells in to.items()], "ga long, gb long, cells array<long>")
    named = blocks.withColumn("ga", F.col("a") % groups).withColumn("gb", F.when(F.col("b") < 0, F.col("b")).otherwise(F.col("b") % groups))
    return named.join(F.broadcast(at), ["ga", "gb"]).select(F.explode("cells").alias("cell"), "ga", "gb", "data").repartition(
        max(1, len(needs)), "cell")


def _fitting(total: int, load, least: int) -> int:
    """The fewest groups, a divisor of GROUPS, whose cells hold few enough arcs; `least` where the graph is not tiny."""
    fits = [g for g in range(1, GROUPS + 1) if GROUPS % g == 0 and (g >= least or total < 10_000)]
    return next((g for g in fits if load(g) * total <= CELL_ARCS), GROUPS)


class Lists:
    """Neighbours of every node of a cell, in one flat array."""

    def __init__(self, nodes: np.ndarray, parts: list[bytes], order: str = "id", turned: bool = False):
        d = max(1, len(nodes))
        n = sum(int(np.frombuffer(p, "<i8", 2)[1]) for p in parts)
        keys = np.empty(n, np.int64)
        ends = keys.view(np.int32).reshape(n, 2)
        degree, at = np.zeros(d, np.int64), 0
        for p in parts:
            own, many, other = unpack(p)
            ends[at:at + len(other), 0] = np.repeat(np.searchsorted(nodes, own), many)
            ends[at:at + len(other), 1] = np.searchsorted(nodes, other)
            if order == "degree":
                degree += np.bincount(ends[at:at + len(other)].ravel(), minlength=d)
            at += len(other)
        self.rank = np.empty(d, np.int32)  # arcs go up the ranks
        self.rank[np.argsort(degree, kind="stable")] = np.arange(d, dtype=np.int32)
        for lo in range(0, n, 1_000_000):
            u, v = self.rank[ends[lo:lo + 1_000_000].T]
            u, v = (np.minimum(u, v), np.maximum(u, v)) if order == "degree" else (v, u) if turned else (u, v)
            keys[lo:lo + 1_000_000] = u.astype(np.int64) * d + v
        keys.sort()
        self.begin = np.searchsorted(keys, np.arange(d + 1, dtype=np.int64) * d)
        flat = keys.view(np.int32)[:n]
        for lo in range(0, n, 1_000_000):  # in place: the written half is behind the part that is read
            flat[lo:lo + 1_000_000] = keys[lo:lo + 1_000_000] % d
        self.flat = flat.copy()

    def of(self, node: int) -> np.ndarray:
        return self.flat[self.begin[node]:self.begin[node + 1]]

    def joined(self, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The lists of some nodes one after the other, and their lengths."""
        lo = self.begin[some]
        many = self.begin[some + 1] - lo
        end = np.cumsum(many)
        return self.flat[np.repeat(lo - end + many, many) + np.arange(end[-1] if len(end) else 0)], many


    def probed(self, some: np.ndarray, near: np.ndarray, mark: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The listed neighbours of some nodes that are in `near` too, and the places of those nodes; `mark` is left empty."""
        more, many = self.joined(some)
        mark[near] = True
        hit = np.flatnonzero(mark[more])
        mark[near] = False
        return more[hit], np.searchsorted(np.cumsum(many), hit, "right")


def _nodes(parts: list[bytes]) -> np.ndarray:
    found, held = [np.empty(0, np.int64)], 0
    for p in parts:
        own, _, other = unpack(p)
        found += [own, sorted_set(other)]
        held += len(found[-1]) + len(own)
        if held > 2_000_000:
            found, held = [sorted_set(np.concatenate(found))], 0
    return sorted_set(np.concatenate(found))


def _group_of(nodes: np.ndarray, blocks: list[tuple[int, int, bytes]]) -> np.ndarray:
    group = np.zeros(len(nodes), np.int64)
    for a, b, p in blocks:
        own, _, other = unpack(p)
        group[np.searchsorted(nodes, own)] = a
        group[np.searchsorted(nodes, other)] = b
    return group


def cliques_in(blocks: list[tuple[int, int, bytes]], corners: tuple[int, ...], order: str) -> int:
    """Cliques with one corner in each of the named groups, extended corner by corner up the order of the nodes.

    Each next corner comes from the lists of the last one and is probed in those of the others. Where
    weights stand among the blocks, a clique counts as the product of its nodes' weights.
    """
    weights = [unpack(p) for _, b, p in blocks if b < 0]
    blocks = [x for x in blocks if x[1] >= 0]
    parts = [p for _, _, p in blocks]
    nodes = _nodes(parts)
    lists = Lists(nodes, parts, order)
    slots = {g: 1 << 4 * i for i, g in enumerate(sorted(set(corners)))}
    group = np.empty(len(nodes), np.int64)
    group[lists.rank[:len(nodes)]] = _group_of(nodes, blocks)
    code = np.zeros(len(nodes), np.int64)
    for g, c in slots.items():
        code[group == g] = c
    w = np.ones(len(nodes), np.int64)
    for node, _, many in weights:  # some nodes may have no arc in this cell
        at = np.searchsorted(nodes, node)
        known = at < len(nodes)
        known[known] = nodes[at[known]] == node[known]
        w[lists.rank[at[known]]] = many[known]
    target = sum(slots[g] for g in corners)
    fits = [np.zeros(len(corners) * max(slots.values()) + 1, bool) for _ in range(4)]  # sums that some of the corners have
    for k in range(1, len(corners)):
        fits[k][[sum(slots[g] for g in c) for c in combinations(corners, k)]] = True
    mark, total = np.zeros(len(nodes), bool), 0
    for u in np.flatnonzero((lists.begin[1:] - lists.begin[:-1] >= len(corners) - 1) & fits[1][code]).tolist():
        near = lists.of(u)
        second = near[fits[2][code[u] + code[near]]] if len(slots) > 1 else near
        more, owner = lists.probed(second, near, mark)
        if not len(more):
            continue
        held, times = (code[u] + code[second])[owner] + code[more], (w[u] * w[second])[owner] * w[more]
        if len(corners) == 4:
            within = second[owner].astype(np.int64) * len(nodes) + more  # sorted, as the lists are
            ok = np.flatnonzero(fits[3][held])
            third, before = more[ok], second[owner[ok]]
            more, owner = lists.probed(third, near, mark)
            if not len(more):
                continue
            key = before[owner].astype(np.int64) * len(nodes) + more
            found = within[np.minimum(np.searchsorted(within, key), len(within) - 1)] == key
            more, owner = more[found], ok[owner[found]]
            held, times = held[owner] + code[more], times[owner] * w[more]
        total += int(times[held == target].sum())
    return total


def clique_count(arcs: DataFrame, k: int, order: str = "id", weights: DataFrame | None = None, least: int = 3) -> DataFrame:
    """Cliques of 3 or 4 nodes over arcs (src < dst, repeats count once); `order` is that of the nodes in a cell.

    With weights (node, w) each counts as the product of its nodes' weights.
    """
    if k not in (3, 4):
        raise ValueError("cliques of 3 or 4 nodes")
    blocks = packed_blocks(arcs, weights)
    total = blocks.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    groups = _fitting(total, lambda g: k * (k - 1) / g**2, least)
    cells = dict(enumerate(combinations_with_replacement(range(groups), k)))
    needs = {i: {x for a, b in combinations(c, 2) for x in ((a, b), (b, a), (a, -1), (b, -1))} for i, c in cells.items()}

    def run(key: tuple[pa.Scalar, ...], cell: pa.Table) -> pa.Table:
        held = list(zip(cell["ga"].to_pylist(), cell["gb"].to_pylist(), cell["data"].to_pylist(), strict=True))
        return pa.table({"cnt": [cliques_in(held, cells[key[0].as_py()], order)]})

    found = _dealt(blocks, groups, needs).groupBy("cell").applyInArrow(run, "cnt long")
    return found.agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("cnt"))


def _typed(classes: DataFrame, path: str, most: int) -> tuple[DataFrame, DataFrame, np.ndarray, np.ndarray]:
    """(classes beside `s`, the number of their type, -1 for none; the hub lines; each type's mask of hubs; its documents).

    Hubs are the lines of the most classes, a type is a set of hubs. Where types are too many, fewer lines are hubs.
    """
    spark, lines = classes.sparkSession, classes.select("node", F.explode("ls").alias("l"))
    top = lines.groupBy("l").agg(F.count("*").alias("k")).where(F.col("k") > HUB_CLASSES).orderBy(F.col("k").desc(), "l").limit(most).collect()
    words, turn = [f"h{i}" for i in range(-(-HUBS // 63))], 0
    while True:
        hubs = spark.createDataFrame([(r["l"], *[1 << i % 63 if i // 63 == w else 0 for w in range(len(words))]) for i, r in enumerate(top)],
                                     "l binary, " + ", ".join(f"{h} long" for h in words))
        masks = lines.join(F.broadcast(hubs), "l").groupBy("node").agg(*[F.bit_or(h).alias(h) for h in words])
        held = written(classes.join(masks, "node", "left").na.fill(0, words), f"{path}/masks-{turn}")
        found = held.where(" or ".join(f"{h} <> 0" for h in words)).groupBy(*words).agg(F.sum("w").alias("n"))
        rows = sorted(found.limit(TYPES + 1).collect())
        if len(rows) <= TYPES:
            break
        top, turn = top[:len(top) // 2], turn + 1
    numbers = spark.createDataFrame([(*r[:-1], i) for i, r in enumerate(rows)], ", ".join(f"{h} long" for h in words) + ", s long")
    held = written(held.join(F.broadcast(numbers), words, "left").na.fill(-1, ["s"]), f"{path}/types")
    return held, hubs, np.array([r[:-1] for r in rows], np.int64).reshape(-1, len(words)), np.array([r["n"] for r in rows], np.int64)


def _meet(masks: np.ndarray, some: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Which of some types have a hub in common with which of others."""
    met = np.zeros((len(some), len(others)), bool)
    for w in masks.T:
        met |= (w[some][:, None] & w[others]) != 0
    return met


def _by_types(thin: DataFrame, masks: np.ndarray, many: np.ndarray) -> DataFrame:
    """Triangles of three hub links, and of two and a thin one: by pairs of types, in blocks, and the documents that meet both."""
    spark, d = thin.sparkSession, len(masks)
    blocks = -(-d // TYPE_BLOCK)
    place = F.floor(F.col("x") / TYPE_BLOCK).cast("long") * blocks + F.floor(F.col("y") / TYPE_BLOCK).cast("long")
    weights = thin.where("s >= 0 and t >= 0").select(F.least("s", "t").alias("x"), F.greatest("s", "t").alias("y"), (F.col("p") * F.col("q")).alias("v"))
    marks = spark.createDataFrame([(i * blocks + j, -1, -1, 0) for i in range(blocks) for j in range(i, blocks)], "block long, x long, y long, v long")
    rows = weights.groupBy("x", "y").agg(F.sum("v").alias("v")).select(place.alias("block"), "x", "y", "v").unionByName(marks)

    def run(key: tuple[pa.Scalar, ...], part: pa.Table) -> pa.Table:
        i, j = divmod(key[0].as_py(), blocks)
        some, others = (np.arange(k * TYPE_BLOCK, min(d, (k + 1) * TYPE_BLOCK)) for k in (i, j))
        both = np.zeros((len(some), len(others)))
        for lo in range(0, d, 8 * TYPE_BLOCK):  # documents, whole numbers below 2^53
            between = np.arange(lo, min(d, lo + 8 * TYPE_BLOCK))
            both += (_meet(masks, some, between) * many[between].astype(float)) @ _meet(masks, others, between).T.astype(float)
        met, both = _meet(masks, some, others), both.astype(np.int64)
        ways = met * many[others]
        # ordered triples and pairs of documents, row by row in whole numbers of any size
        triples = sum(n * v for n, v in zip(many[some].tolist(), (ways * both).sum(axis=1).tolist(), strict=True)) * (1 if i == j else 2)
        pairs = sum(n * v for n, v in zip(many[some].tolist(), ways.sum(axis=1).tolist(), strict=True)) * (1 if i == j else 2)
        x, y, v = (part[c].to_numpy() for c in ("x", "y", "v"))
        at = np.flatnonzero(x >= 0)
        mixed = sum(n * v for n, v in zip(both[x[at] - some[0], y[at] - others[0]].tolist(), v[at].tolist(), strict=True))
        return pa.table({"mixed": pa.array([Decimal(mixed)], pa.decimal128(38, 0)), "ordered": pa.array([Decimal(triples - 3 * pairs)], pa.decimal128(38, 0))})

    found = rows.groupBy("block").applyInArrow(run, "mixed decimal(38,0), ordered decimal(38,0)")
    sums = found.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in found.columns])
    # one document three times is one triple and was taken off three times
    return sums.select((F.col("mixed") + (F.col("ordered") + F.lit(2 * int(many.sum()))) / 6).cast("long").alias("cnt"))


def _by_middles(thin: DataFrame, masks: np.ndarray) -> DataFrame:
    """Triangles of two thin links and a hub link: at each class, pairs of the documents it is linked to whose types meet."""
    ends = thin.select(F.col("src").alias("node"), F.col("p").alias("w"), F.col("t").alias("s"), F.col("q").alias("c")).unionByName(
        thin.select(F.col("dst").alias("node"), F.col("q").alias("w"), "s", F.col("p").alias("c")))

    def run(batches):
        for batch in batches:
            total = 0
            for one in batch.to_pylist():
                s, c = (np.array([x[k] for x in one["near"]], np.int64) for k in ("s", "c"))
                for lo in range(0, len(s), 1_000):
                    some = s[lo:lo + 1_000]
                    total += one["w"] * int(c[lo:lo + 1_000] @ (_meet(masks, some, s) @ c))
                total -= one["w"] * int(c.sum())
            yield pa.RecordBatch.from_arrays([pa.array([Decimal(total // 2)], pa.decimal128(38, 0))], names=["cnt"])

    near = ends.where("s >= 0").groupBy("node", "w", "s").agg(F.sum("c").alias("c"))
    lists = near.groupBy("node", "w").agg(F.collect_list(F.struct("s", "c")).alias("near")).select("w", "near")  # no longer than the types
    return lists.mapInArrow(run, "cnt decimal(38,0)").agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("cnt"))


def class_triangles(classes: DataFrame, hubs: int = HUBS) -> DataFrame:
    """Triangles of a graph whose nodes stand in classes (node, w, ls) of alike ones: w nodes, all linked, with the links of ls.

    The links of hub lines are never listed: nodes of the same hubs are one type, and two types with a hub in common
    are linked throughout. The other, thin links are arcs between classes. Triangles are counted by their thin links:
    none or one (by types), two (at the class in the middle), three (as cliques of the arcs and within classes).
    """
    path = folder(classes.sparkSession, "classes")
    classes = written(classes, f"{path}/classes")
    typed, tops, masks, many = _typed(classes, path, hubs)
    words = [c for c in typed.columns if c.startswith("h")]
    lines = classes.select("node", F.explode("ls").alias("l")).join(F.broadcast(tops), "l", "left_anti")
    ends = _pairs(lines, "l", "node").join(typed.select("node", "w", "s", *words).toDF("src", "p", "s", *words), "src").join(
        typed.select("node", "w", "s", *words).toDF("dst", "q", "t", *[f"{h}t" for h in words]), "dst")
    thin = written(ends.where(" and ".join(f"({h} & {h}t) = 0" for h in words)).select("src", "dst", "p", "q", "s", "t"), f"{path}/thin")
    w = typed.select("node", "w")
    parts = [clique_count(thin.select("src", "dst"), 3, "id", w)]
    if len(masks):
        parts += [_by_types(thin, masks, many), _by_middles(thin, masks)]
    # the links within a class of no type are thin
    two = "(case when s < 0 then p * (p - 1) div 2 * q else 0 end) + (case when t < 0 then q * (q - 1) div 2 * p else 0 end)"
    parts.append(thin.agg(F.sum(F.expr(two)).alias("cnt")))
    parts.append(typed.where("s < 0 and w > 2").agg(F.sum(F.expr("w * (w - 1) * (w - 2) div 6")).alias("cnt")))
    return reduce(DataFrame.unionByName, parts).agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("cnt"))


def squares_in(out: Lists, into: Lists, above: Lists, starts: np.ndarray, d: int, method: str) -> int:
    """Squares x0 < x1 < x2 < x3 from arcs x0-x1 and x0-x3 (out), x1-x2 (into) and x2-x3, listed at x3 (above).

    pairwise: both halves are joined, counted by (x0, x2) and joined on it. probing: x0 is extended by x3,
    then by x2, which probes the counted candidates of x1.
    """
    counts, total = np.zeros(d, np.int64), 0
    for u in starts.tolist():
        near = out.of(u)
        low, _ = into.joined(near)
        if len(low) == 0:
            continue
        high, _ = above.joined(near)
        if method == "pairwise":
            x, n = np.unique(low, return_counts=True)
            y, m = np.unique(high, return_counts=True)
            at = np.minimum(np.searchsorted(y, x), max(0, len(y) - 1))
            total += int((n * m[at])[y[at] == x].sum()) if len(y) else 0
        else:
            np.add.at(counts, low, 1)
            total += int(counts[high].sum())
            counts[low] = 0
    return total


def square_count(arcs: DataFrame, method: str, least: int = 4) -> DataFrame:
    """Squares whose corners increase all the way round, over arcs (src < dst, repeats count once).

    Cut by the groups of two opposite corners, x0 and x2.
    """
    blocks = packed_blocks(arcs)
    total = blocks.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    groups = _fitting(total, lambda g: 2 / g, least)
    cells = dict(enumerate(product(range(groups), repeat=2)))
    needs = {i: {(a, b) for a, b in product(range(groups), repeat=2) if a in (x, z) or b == z} for i, (x, z) in cells.items()}

    def run(key: tuple[pa.Scalar, ...], cell: pa.Table) -> pa.Table:
        x, z = cells[key[0].as_py()]
        held = list(zip(cell["ga"].to_pylist(), cell["gb"].to_pylist(), cell["data"].to_pylist(), strict=True))
        nodes = _nodes([p for _, _, p in held])
        out = Lists(nodes, [p for a, _, p in held if a == x])
        into = Lists(nodes, [p for _, b, p in held if b == z])
        above = Lists(nodes, [p for a, _, p in held if a == z], turned=True)
        starts = np.flatnonzero(out.begin[1:] - out.begin[:-1] > 1)
        return pa.table({"cnt": [squares_in(out, into, above, starts, len(nodes), method)]})

    found = _dealt(blocks, groups, needs).groupBy("cell").applyInArrow(run, "cnt long")
    return found.agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("cnt"))
