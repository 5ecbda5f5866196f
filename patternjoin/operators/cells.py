"""One-round joins: tuples are dealt to cells of the output space, a kernel joins each cell."""

from __future__ import annotations

import math
from decimal import Decimal
from itertools import product as cartesian

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel.gap import INF, Counters, Options, gap_counts, gap_join
from ..kernel.intersect import flat_count, trie_join
from ..query.model import JoinQuery, choose_order, is_beta_acyclic, is_neo, skeleton
from ..streaming.views import folder
from .bind import Relations, bind
from .blocks import packed_blocks, unpack
from .recursive import written

#: Tuples a cell of the gap-box join should hold: its Python objects take about 1 kB a tuple.
GAP_TUPLES = 40_000
#: Tuples a cell of the hypercube join should hold, in flat arrays; the same where they come in packed blocks, and those of a block's piece.
FLAT_TUPLES, PACKED_TUPLES, PIECE_TUPLES = 1_000_000, 4_000_000, 500_000
#: Tuples a routed cell may get for each one it should keep: they are reduced in flat arrays before objects are made.
ROUTED = 4
#: Tasks over which routed cells are spread at most.
ROUTED_TASKS = 512


def best_shares(q: JoinQuery, sizes: dict[str, int], cells: int) -> dict[str, int]:
    """Integer shares of at most `cells` cells with the fewest tuples sent."""
    options = [2**k for k in range(cells.bit_length())]
    best = None
    for shares in cartesian(options, repeat=len(q.variables)):
        total = 1
        for s in shares:
            total *= s
        if total > cells:
            continue
        of = dict(zip(q.variables, shares, strict=True))
        sent = sum(sizes[a.rel] * total // _prod(of[v] for v in set(a.vars)) for a in q.atoms)
        load = sum(sizes[a.rel] / _prod(of[v] for v in set(a.vars)) for a in q.atoms)
        key = (load, sent)
        if best is None or key < best[0]:
            best = (key, of)
    return best[1]


def _prod(values) -> int:
    out = 1
    for v in values:
        out *= v
    return out


def fitting_shares(q: JoinQuery, sizes: list[int], most: int, least: dict[str, int] | None = None, fixed: tuple[str, ...] = ()) -> dict[str, int]:
    """Shares of at least `least` so that a cell gets at most `most` tuples, as sizes of the atoms and hashing have it.

    Doubled one by one, each time the variable that leaves a cell the fewest tuples, ties to the fewest sent.
    Fixed variables are not doubled; atoms of these alone do not count.
    """
    shares = {v: 1 for v in q.variables} | (least or {})
    free = [v for v in q.variables if v not in fixed]

    def load(of: dict[str, int]) -> float:
        return sum(n / _prod(of[v] for v in set(a.vars)) for a, n in zip(q.atoms, sizes, strict=True) if set(a.vars) & set(free))

    def next_(v: str) -> tuple[float, float]:
        of = shares | {v: 2 * shares[v]}
        return load(of), load(of) * _prod(of.values())

    while load(shares) > most:
        v = min(free, key=next_)
        shares[v] *= 2
    return shares


def _reduced(q: JoinQuery, parts: list[list[np.ndarray]], rounds: int = 10) -> list[list[np.ndarray]]:
    """A cell's atoms without the tuples whose value of some variable another atom lacks."""
    owns = [list(dict.fromkeys(a.vars)) for a in q.atoms]
    for _ in range(rounds):
        before = sum(len(p[0]) for p in parts)
        for v in q.variables:
            uses = [(i, own.index(v)) for i, own in enumerate(owns) if v in own]
            if len(uses) > 1:
                common = np.unique(parts[uses[0][0]][uses[0][1]])
                for i, k in uses[1:]:
                    common = np.intersect1d(common, parts[i][k])
                for i, k in uses:
                    left = np.isin(parts[i][k], common)
                    parts[i] = [c[left] for c in parts[i]]
        if sum(len(p[0]) for p in parts) == before:
            break
    return parts


def _packed_kernel(q: JoinQuery, order, shares: dict[str, int]):
    """Counts a cell whose atoms come as packed blocks: each block is there once, whatever atoms and columns it serves."""
    def run(key: tuple[pa.Scalar, ...], cell: pa.Table) -> pa.Table:
        left, place = key[0].as_py(), {}
        for v in reversed(q.variables):
            left, place[v] = divmod(left, shares[v])
        rels, a, b, data = (cell[c].to_pylist() for c in ("rel", "a", "b", "data"))
        found: dict[tuple[int, ...], list[np.ndarray]] = {}
        atoms = []
        for atom in q.atoms:
            u, v = atom.vars
            own = tuple(i for i in range(len(rels)) if rels[i] == atom.rel and a[i] % shares[u] == place[u] and b[i] % shares[v] == place[v])
            if own not in found:
                parts = [unpack(data[i]) for i in own]
                found[own] = [np.concatenate([np.empty(0, np.int64), *[np.repeat(src, many) for src, many, _ in parts]]),
                              np.concatenate([np.empty(0, np.int64), *[dst for _, _, dst in parts]])]
            atoms.append((atom.vars, found[own]))
        return pa.table({"cnt": [flat_count(atoms, order, q.filters)]})

    return run, "cnt long"


def _packed_cells(q: JoinQuery, rels: Relations, counted: dict[str, int], shares: dict[str, int]) -> DataFrame:
    """(cell, rel, a, b, data): every relation packed once by the hashes of both columns, every block sent to the cells of the atoms it serves.

    Shares are powers of two, so the groups of the widest one are parts of those of the others.
    """
    spark = next(iter(rels.values())).sparkSession
    needs: dict[tuple[str, int, int], set[int]] = {}
    groups = {r: max(shares[v] for a in q.atoms if a.rel == r for v in a.vars) for r in counted}
    for number, cell in enumerate(cartesian(*[range(shares[v]) for v in q.variables])):
        place = dict(zip(q.variables, cell, strict=True))
        for atom in q.atoms:
            u, v = atom.vars
            g = groups[atom.rel]
            for a, b in cartesian(range(place[u], g, shares[u]), range(place[v], g, shares[v])):
                needs.setdefault((atom.rel, a, b), set()).add(number)
    at = spark.createDataFrame([(*k, sorted(cells)) for k, cells in needs.items()], "rel string, a long, b long, cells array<long>")
    packed = None
    for r, n in counted.items():
        g = groups[r]
        arcs = rels[r].toDF("src", "dst").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null")
        one = packed_blocks(arcs, None, g, max(1, math.ceil(n / g**2 / PIECE_TUPLES))).select(F.lit(r).alias("rel"), "a", "b", "data")
        packed = one if packed is None else packed.unionByName(one)
    return packed.join(F.broadcast(at), ["rel", "a", "b"]).select(F.explode("cells").alias("cell"), "rel", "a", "b", "data").repartition(
        min(ROUTED_TASKS, _prod(shares.values())), "cell")


def _kernel(q: JoinQuery, order, method: str, kept, options: Options, mode: str, routed: bool = False):
    names = [f"c{i}" for i in range(max(len(set(a.vars)) for a in q.atoms))]

    def run(cell: pa.Table) -> pa.Table:
        number = cell["atom"].to_numpy()
        if method == "trie" and mode == "count" and max(len(set(a.vars)) for a in q.atoms) <= 2:
            columns = {c: cell[c].to_numpy() for c in names}
            parts = [(own, [columns[c][number == i].astype(np.int64) for c in names[:len(own)]]) for i, a in enumerate(q.atoms) for own in [tuple(dict.fromkeys(a.vars))]]
            return pa.table({"cnt": [flat_count(parts, order, q.filters)]})
        owns = [tuple(dict.fromkeys(a.vars)) for a in q.atoms]
        parts = []
        for i, own in enumerate(owns):
            mine = cell.filter(pa.array(number == i))
            parts.append([mine[c].to_numpy() for c in names[:len(own)]])
        if routed:
            parts = _reduced(q, parts)
        atoms = [(own, list(zip(*[c.tolist() for c in part], strict=True))) for own, part in zip(owns, parts, strict=True)]
        counters = Counters()
        if method == "points":
            numbers = gap_counts(atoms, order, counters)
            if mode == "by":
                return pa.table({order[0]: pa.array(list(numbers), pa.int64()),
                                 "w": pa.array(list(map(Decimal, numbers.values())), pa.decimal128(38, 0))})
            return pa.table({"cnt": [sum(numbers.values())]} | {k: [v] for k, v in counters.row().items()})
        if mode == "boxes":
            boxes: list = []
            n = sum(1 for _ in gap_join(atoms, order, kept, options, counters, q.filters, boxes))
            mark = lambda x: None if abs(x) >= INF else x
            return pa.table({"pattern": [" ".join("*" if p is None else str(p) for p in b[0]) for b in boxes] + ["outputs"],
                             "lo": pa.array([mark(b[1]) for b in boxes] + [0], pa.int64()),
                             "hi": pa.array([mark(b[2]) for b in boxes] + [n], pa.int64())})
        found = trie_join(atoms, order, q.filters) if method == "trie" else gap_join(atoms, order, kept, options, counters, q.filters)
        if mode == "rows":
            out = list(found)
            return pa.table({v: pa.array([p[order.index(v)] for p in out], pa.int64()) for v in q.variables})
        n = sum(1 for _ in found)
        return pa.table({"cnt": [n]} | ({k: [v] for k, v in counters.row().items()} if method == "gap" else {}))

    if mode == "by":
        return run, f"{order[0]} long, w decimal(38,0)"
    if mode == "boxes":
        return run, "pattern string, lo long, hi long"
    schema = ", ".join(f"{v} long" for v in q.variables) if mode == "rows" else "cnt long"
    if method != "trie" and mode != "rows":
        schema += "".join(f", {k} long" for k in Counters().row())
    return run, schema


def _join_cells(q: JoinQuery, dealt: DataFrame, order, method: str, kept, options: Options, mode: str, routed: bool = False,
                shares: dict[str, int] | None = None) -> DataFrame:
    run, schema = _packed_kernel(q, order, shares) if method == "packed" else _kernel(q, order, method, kept, options, mode, routed)
    found = dealt.groupBy("cell").applyInArrow(run, schema)
    if mode in ("rows", "by", "boxes"):
        return found
    sums = [F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in found.columns]
    return found.agg(*sums)


def _padded(q: JoinQuery, df: DataFrame, i: int, cell) -> DataFrame:
    own = list(dict.fromkeys(q.atoms[i].vars))
    width = max(len(set(a.vars)) for a in q.atoms)
    columns = [(F.col(own[k]) if k < len(own) else F.lit(None)).cast("long").alias(f"c{k}") for k in range(width)]
    return df.select(cell.alias("cell"), F.lit(i).alias("atom"), *columns)


def hypercube_join(q: JoinQuery, rels: Relations, shares: dict[str, int] | None = None, order: tuple[str, ...] | None = None,
                   mode: str = "count", cells: int = 64, sizes: dict[str, int] | None = None, cell_tuples: int | None = None) -> DataFrame:
    """Every variable is hashed to a share; an atom's tuple goes to all cells that agree with it; one shuffle.

    Any arity. Without given shares the relations are counted, and `cells` grows until a cell holds at most
    `cell_tuples` tuples: counts over atoms of one or two variables keep them in flat arrays, the rest as objects.
    Where a count's atoms all have two variables, tuples are sent in packed blocks (one or two bytes a tuple).
    """
    order = order or choose_order(q, cyclic=True)
    if not shares:
        path = folder(rels[q.atoms[0].rel].sparkSession, "cube")
        rels = {r: written(rels[r], f"{path}/{r}") for r in dict.fromkeys(a.rel for a in q.atoms)}
        counted = {r: df.count() for r, df in rels.items()}
        flat = mode == "count" and max(len(set(a.vars)) for a in q.atoms) <= 2
        packed = flat and all(len(a.vars) == len(set(a.vars)) == 2 for a in q.atoms)
        most = cell_tuples or (PACKED_TUPLES if packed else FLAT_TUPLES if flat else GAP_TUPLES)
        shares = fitting_shares(q, [counted[a.rel] for a in q.atoms], most, best_shares(q, sizes or counted, cells))
        if packed:
            return _join_cells(q, _packed_cells(q, rels, counted, shares), order, "packed", None, Options(), mode, False, shares)
    dealt = None
    for i, a in enumerate(q.atoms):
        df = bind(a, rels)
        cell = F.lit(0)
        for v in q.variables:
            if v in a.vars:
                place = F.pmod(F.xxhash64(v), F.lit(shares[v]))
            else:
                df = df.withColumn(f"__{v}", F.explode(F.sequence(F.lit(0), F.lit(shares[v] - 1))))
                place = F.col(f"__{v}")
            cell = cell * shares[v] + place
        part = _padded(q, df, i, cell.cast("long"))
        dealt = part if dealt is None else dealt.unionByName(part)
    return _join_cells(q, dealt, order, "trie", None, Options(), mode)


def _cuts(atoms: list[DataFrame], first: str, jobs: int) -> list[int]:
    """Values that cut the first variable's occurrences in about equal parts."""
    if jobs < 2:
        return []
    values = None
    for df in atoms:
        if first in df.columns:
            one = df.select(F.col(first).alias("v"))
            values = one if values is None else values.unionByName(one)
    marks = values.agg(F.percentile_approx("v", [k / jobs for k in range(1, jobs)], max(10_000, 20 * jobs))).first()[0] or []
    return sorted({int(m) for m in marks})


def _placed(df: DataFrame, first: str, cuts: list[int]) -> DataFrame:
    """Beside the variables, as longs, `part`: how many of the cuts are below the first variable."""
    ends = np.array(cuts, np.int64)

    def run(batches):
        for b in batches:
            part = np.searchsorted(ends, b.column(first).to_numpy(), "left")
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(part, pa.int64())], names=[*b.schema.names, "part"])

    return df.select(*[F.col(v).cast("long").alias(v) for v in df.columns]).mapInArrow(
        run, ", ".join(f"`{v}` long" for v in df.columns) + ", part long")


def _routes(q: JoinQuery, order: tuple[str, ...]) -> dict[int, tuple[int, str]] | None:
    """For each atom without the first variable an atom with it and a variable that both have; None if some atom has no such."""
    found = {}
    hosts = [i for i, a in enumerate(q.atoms) if order[0] in a.vars]
    for i, a in enumerate(q.atoms):
        if i not in hosts:
            shared = [(j, v) for v in order for j in hosts if v in a.vars and v in q.atoms[j].vars]
            if not shared:
                return None
            found[i] = shared[0]
    return found


def _routed(q: JoinQuery, atoms: list[DataFrame], order: tuple[str, ...], jobs: int, cell_tuples: int, routes: dict[int, tuple[int, str]], path: str) -> DataFrame:
    """The atoms' tuples dealt to cells: those with the first variable by its ranges, once each, the others to the parts that have their value.

    Each part's tuples are counted before any is sent; a part with over ROUTED * `cell_tuples` of them is cut further,
    by hashing its other variables.
    """
    first, others = order[0], order[1:]
    hosts = [i for i in range(len(atoms)) if i not in routes]
    jobs = max(jobs, math.ceil(2 * sum(atoms[i].count() for i in hosts) / cell_tuples))
    cuts = _cuts(atoms, first, jobs)
    placed = {i: _placed(atoms[i], first, cuts) for i in hosts}
    marks = {(j, v): written(placed[j].select("part", v).distinct(), f"{path}/marks-{j}-{v}") for j, v in dict.fromkeys(routes.values())}
    loads = None
    for i, df in enumerate(atoms):
        if i in routes:
            v = routes[i][1]
            one = marks[routes[i]].join(df.groupBy(v).agg(F.count("*").alias("n")), v).groupBy("part").agg(F.sum("n").alias("n"))
        else:
            one = placed[i].groupBy("part").agg(F.count("*").alias("n"))
        one = one.select("part", F.lit(i).alias("atom"), "n")
        loads = one if loads is None else loads.unionByName(one)
    sizes = [F.coalesce(F.sum(F.when(F.col("atom") == i, F.col("n"))), F.lit(0)).alias(f"n{i}") for i in range(len(atoms))]
    most = ROUTED * cell_tuples
    large = loads.groupBy("part").agg(F.sum("n").alias("n"), *sizes).where(F.col("n") > most).collect()
    cut = [(r["part"], fitting_shares(q, [r[f"n{i}"] for i in range(len(atoms))], most, fixed=(first,))) for r in large]
    subs = max((_prod(of.values()) for _, of in cut), default=1)
    if cut:
        shares = atoms[0].sparkSession.createDataFrame([(part, *[of[v] for v in others]) for part, of in cut], "part long" + "".join(f", `__n{v}` int" for v in others))
    dealt = None
    for i, df in enumerate(atoms):
        df = marks[routes[i]].join(df.select(*[F.col(v).cast("long").alias(v) for v in df.columns]), routes[i][1]) if i in routes else placed[i]
        cell = F.lit(0)
        if cut:
            df = df.join(F.broadcast(shares), "part", "left")
            for v in others:
                n = F.coalesce(F.col(f"__n{v}"), F.lit(1))
                if v not in atoms[i].columns:
                    df = df.withColumn(f"__{v}", F.explode(F.sequence(F.lit(0), n - 1)))
                cell = cell * n + (F.pmod(F.xxhash64(v), n) if v in atoms[i].columns else F.col(f"__{v}"))
        part = _padded(q, df, i, (F.col("part") * subs + cell).cast("long"))
        dealt = part if dealt is None else dealt.unionByName(part)
    return dealt.repartition(max(1, min(ROUTED_TASKS, len(cuts) + 1)), "cell")


def partitioned_gap_join(q: JoinQuery, rels: Relations, parts: int = 8, granularity: int | None = None,
                         order: tuple[str, ...] | None = None, options: Options = Options(), mode: str = "count",
                         points: bool = False, cell_tuples: int = GAP_TUPLES) -> DataFrame:
    """The output space cut in equal parts of the first variable; each part is a job of the gap-box join.

    Atoms with the first variable are routed by range; the others go to every part, which is the price of
    this split (messages and prefix extension avoid it). Where a part would hold more than `cell_tuples`
    tuples, the space is cut along the other variables too, by hash, as the counted sizes ask: a job's
    memory stays the same however large the relations are. In cyclic queries whose atoms all meet one with
    the first variable, the others go just to the parts that have their value (`_routed`): fewer copies, more
    and smaller parts. Atoms of one variable are applied to the other atoms before they are dealt. Counts come with the kernel's counters. With
    `points` numbers are kept for the points of the ledgers and no binding is listed (nested elimination
    orders); mode="by" then gives (first variable, w). mode="boxes" gives the certificate: every gap box
    that was found, and a row `outputs` with their number in hi.
    """
    acyclic = is_beta_acyclic(q)
    order = order or choose_order(q)
    jobs = parts * (granularity or (1 if acyclic else 8))
    if points and (q.filters or not is_neo(q, order)):
        raise ValueError("numbers for points need a nested elimination order and no comparisons")
    kept = None if acyclic else skeleton(q, order)[0]
    first = order[0]
    path = folder(rels[q.atoms[0].rel].sparkSession, "gap")
    held = {r: written(rels[r], f"{path}/{r}") for r in dict.fromkeys(a.rel for a in q.atoms)}
    atoms, narrowed = [bind(a, held) for a in q.atoms], set()
    for i, a in enumerate(q.atoms):
        for u, b in enumerate(q.atoms):
            if u != i and len(set(a.vars)) > 1 and len(set(b.vars)) == 1 and b.vars[0] in a.vars:
                atoms[i] = atoms[i].join(atoms[u], b.vars[0], "left_semi")
                narrowed.add(i)
    atoms = [written(df, f"{path}/{i}") if i in narrowed else df for i, df in enumerate(atoms)]
    routes = None if acyclic or mode == "boxes" else _routes(q, order)  # a certificate is one of the whole relations
    if routes is not None:
        dealt = _routed(q, atoms, order, jobs, cell_tuples, routes, path)
        return _join_cells(q, dealt, order, "gap", kept, options, mode, routed=True)
    shares = fitting_shares(q, [df.count() for df in atoms], cell_tuples, {first: jobs})
    cuts = _cuts(atoms, first, shares[first])
    bounds = F.array(*[F.lit(c).cast("long") for c in cuts]) if cuts else F.array().cast("array<bigint>")
    dealt = None
    for i, df in enumerate(atoms):
        own, cell = df.columns, F.lit(0).cast("long")
        for v in order:
            n = len(cuts) + 1 if v == first else shares[v]
            if v not in own:
                df = df.withColumn(f"__{v}", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))) if n > 1 else df
                place = F.col(f"__{v}") if n > 1 else F.lit(0)
            else:
                place = F.size(F.filter(bounds, lambda c: c < F.col(first))) if v == first else F.pmod(F.xxhash64(v), F.lit(n))
            cell = cell * n + place
        part = _padded(q, df, i, cell.cast("long"))
        dealt = part if dealt is None else dealt.unionByName(part)
    found = _join_cells(q, dealt, order, "points" if points else "gap", kept, options, mode)
    if mode == "by":
        return found.groupBy(first).agg(F.sum("w").cast("decimal(38,0)").alias("w"))
    return found
