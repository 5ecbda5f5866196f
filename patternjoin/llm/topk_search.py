"""Exact top-k inner products by score-at-a-time over impact-ordered posting segments.

A block of vectors is inverted: the posting list of a dimension holds (row, value) for the rows
that are not zero there, cut into segments by quantised impact (2^(l-1) <= |value| < 2^l). A batch
of queries takes the segments level by level, the largest impacts of all dimensions first, and adds
each into the rows' accumulators. After a level it knows, for each row, a limit on what smaller impacts
can still add (the norm of the row's unprocessed part times the query's norm). It stops when no row
outside its possible members can reach its k-th best proven score; the possible members are then
rescored exactly in integers.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK_ROWS = 8192
QUERY_ROWS = 128


class ImpactIndex:
    """Inverted lists of one block of integer vectors, in segments of equal impact level."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        self.ids = ids
        self.vectors = vectors
        magnitude = np.abs(vectors)
        self.wide = int(magnitude.max(initial=0))
        row, dim = np.nonzero(vectors)
        value = vectors[row, dim]
        level = np.frexp(magnitude[row, dim].astype(np.float64))[1]  # bit length of the magnitude
        squares = np.zeros(len(ids))
        np.add.at(squares, row, value.astype(np.float64) ** 2)
        # postings by level, largest first, then by dimension: a segment is a stretch of these arrays
        order = np.lexsort((row, dim, -level))
        row, dim, value, level = row[order], dim[order], value[order].astype(np.float64), level[order]
        edge = np.flatnonzero(np.concatenate([[True], (level[1:] != level[:-1]) | (dim[1:] != dim[:-1])])) if len(row) else np.empty(0, np.int64)
        ends = np.append(edge[1:], len(row))
        self.rows, self.values = row, value
        self.levels: list[tuple[list[tuple[int, int, int]], np.ndarray]] = []
        segments = list(zip(level[edge].tolist(), dim[edge].tolist(), edge.tolist(), ends.tolist(), strict=True))
        for l in dict.fromkeys(x[0] for x in segments):
            own = [x[1:] for x in segments if x[0] == l]
            lo, hi = own[0][1], own[-1][2]
            np.subtract.at(squares, row[lo:hi], value[lo:hi] ** 2)
            # a hair above the true norm, so that rounding cannot make the limit too low
            self.levels.append((own, np.sqrt(np.maximum(squares, 0.0)) * (1 + 1e-9) + 1e-6))

    def search(self, query_ids: np.ndarray, queries: np.ndarray, k: int):
        """(query index, rank order is left to the caller, row index, exact score) of the k best per query."""
        n = len(self.ids)
        partial = np.zeros((n, len(queries)))  # a posting touches all queries of the batch in one stretch of memory
        q = queries.astype(np.float64)
        q_norm = np.sqrt((q * q).sum(axis=1)) * (1 + 1e-9)
        own = self.ids[:, None] == query_ids[None, :]
        open_rows = None
        kth = min(k, n) - 1
        for segments, rest_norm in self.levels:
            for dim, lo, hi in segments:  # a row stands once in a list, so no sum is lost
                asking = np.flatnonzero(q[:, dim])
                if len(asking):
                    partial[self.rows[lo:hi]] += self.values[lo:hi, None] * q[None, :, dim]
            limit = rest_norm[:, None] * q_norm[None, :]
            slack = 1e-9 * (np.abs(partial) + limit) + 1e-6
            low = np.where(own, -np.inf, partial - limit - slack)
            floor = -np.partition(-low, kth, axis=0)[kth]
            open_rows = (partial + limit + slack >= floor[None, :]) & ~own
            if open_rows.sum() <= 4 * k * len(queries):
                break  # proven: whatever is left out cannot be among the k best
        if open_rows is None:
            open_rows = ~own
        qi, ri = np.nonzero(open_rows.T)
        exact = np.empty(len(qi), np.int64)
        # 64-bit sums are exact while no product sum can pass 2^63; wider values go through Python integers
        wide = max(self.wide, int(np.abs(queries).max(initial=0)))
        if wide * wide * max(1, queries.shape[1]) < 2**62:
            for lo in range(0, len(qi), 1 << 16):
                s = slice(lo, lo + (1 << 16))
                exact[s] = np.einsum("ij,ij->i", queries[qi[s]], self.vectors[ri[s]])
        else:
            for i, (a, b) in enumerate(zip(qi.tolist(), ri.tolist(), strict=True)):
                exact[i] = sum(x * y for x, y in zip(queries[a].tolist(), self.vectors[b].tolist(), strict=True))
        order = np.lexsort((self.ids[ri], -exact, qi))
        qi, ri, exact = qi[order], ri[order], exact[order]
        place = np.arange(len(qi)) - np.searchsorted(qi, qi)
        best = place < k
        return qi[best], ri[best], exact[best]


def exact_top_k(vectors: DataFrame, k: int = 5, query_divisor: int = 50, scale: int = 256, id_column: str = "vec_id",
                vector_column: str = "embedding", block_rows: int = BLOCK_ROWS, query_rows: int = QUERY_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): the k largest integer inner products of each query.

    Components become floor(scale * x), x as double. Vectors that are null, hold null or non-finite
    components, or have a null id take no part; only vectors of equal length are compared. Rows that
    repeat an id are separate candidates for other queries and a query's own id is never a candidate;
    repeated query rows count once. Ties go to the smaller vec_id. Fewer rows than k give all of them;
    an empty table gives no rows.

    Both sides travel as packed blocks: every block of rows meets every block of queries, so
    nothing is broadcast and a task holds one block and one batch of queries.
    """
    v = F.col(vector_column)
    usable = (v.isNotNull() & F.col(id_column).isNotNull() & (F.size(v) > 0)
              & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))))
    ints = (vectors.where(usable).select(
        F.col(id_column).cast("long").alias("vec_id"),
        F.transform(v, lambda x: F.floor(x.cast("double") * scale).cast("long")).alias("q"))
        .withColumn("dims", F.size("q")))

    def pack(rows_at_most: int):
        def run(batches):
            held: dict[int, list] = {}

            def out(dims):
                parts = held.pop(dims)
                ids = np.concatenate([p[0] for p in parts])
                data = np.concatenate([p[1] for p in parts])
                small = np.abs(data).max(initial=0) < 32_768
                return pa.RecordBatch.from_arrays(
                    [pa.array([dims], pa.int32()), pa.array([len(ids)], pa.int32()), pa.array([bool(small)]),
                     pa.array([ids.tobytes()], pa.binary()),
                     pa.array([data.astype(np.int16 if small else np.int64).tobytes()], pa.binary())],
                    names=["dims", "n", "small", "ids", "data"])

            for batch in batches:
                dims = batch.column(2).to_numpy(zero_copy_only=False)
                for d in np.unique(dims).tolist():
                    at = np.nonzero(dims == d)[0]
                    part = batch.take(pa.array(at))
                    ids = part.column(0).to_numpy(zero_copy_only=False)
                    data = part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
                    for lo in range(0, len(ids), rows_at_most):
                        held.setdefault(d, []).append((ids[lo:lo + rows_at_most], data[lo:lo + rows_at_most]))
                        if sum(len(p[0]) for p in held[d]) >= rows_at_most:
                            yield out(d)
            for d in list(held):
                yield out(d)

        return run

    packed = "dims int, n int, small boolean, ids binary, data binary"
    rows = ints.mapInArrow(pack(block_rows), packed)
    queries = (ints.where(F.col("vec_id") % query_divisor == 0).dropDuplicates(["vec_id"])
               .mapInArrow(pack(query_rows), packed)
               .select("dims", *[F.col(c).alias(f"q_{c}") for c in ("n", "small", "ids", "data")]))
    # few, large rows on both sides: one pair of blocks is one unit of work. Blocks of rows are dealt
    # to slots and every batch of queries goes to all slots, so that pairs spread over the cluster.
    slots = max(1, -(-ints.count() // block_rows))
    rows = rows.withColumn("slot", F.pmod(F.xxhash64("ids"), F.lit(slots)).cast("int"))
    queries = queries.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(slots - 1))))
    pairs = rows.join(queries, ["dims", "slot"])

    def vectors_of(n, small, ids, data, dims):
        return (np.frombuffer(ids, np.int64, n),
                np.frombuffer(data, np.int16 if small else np.int64).astype(np.int64).reshape(n, dims))

    def search(batches):
        last, index = None, None
        for batch in batches:
            for r in batch.to_pylist():
                if r["ids"] != last:
                    last = r["ids"]
                    index = ImpactIndex(*vectors_of(r["n"], r["small"], r["ids"], r["data"], r["dims"]))
                q_ids, q = vectors_of(r["q_n"], r["q_small"], r["q_ids"], r["q_data"], r["dims"])
                qi, ri, score = index.search(q_ids, q, k)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(q_ids[qi]), pa.array(index.ids[ri]), pa.array(score)],
                    names=["query_id", "vec_id", "score"])

    found = pairs.mapInArrow(search, "query_id long, vec_id long, score long")
    # each block has sent k rows of a query at most; sorting structs by (-score, vec_id) ranks them
    best = found.groupBy("query_id").agg(
        F.slice(F.sort_array(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k).alias("top"))
    return best.select("query_id", F.posexplode("top").alias("pos", "x")).select(
        "query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"),
        (-F.col("x.s")).alias("score"))
