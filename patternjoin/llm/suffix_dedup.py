"""Removing repeated byte strings with a two-stage suffix array.

1. Every text is winnowed: each window of `length` bytes names one anchor inside it, the
   rightmost smallest hash of its 32-byte strings. Equal windows name equal anchors, so windows
   of an anchor that occurs once in the corpus cannot be repeated and need no sorting.
2. The windows of one anchor occurrence form a run; the bytes they span are its context. A
   context that occurs twice is repeated as a whole. Contexts that share their anchor with other
   contexts are laid end to end and suffix-sorted: only suffixes smaller than their successors
   are sorted directly, bucket scans induce the others, and common prefixes of neighbours show
   the windows that occur again.
3. Anchors with very many contexts are sorted in chunks; windows that stay unique in their chunk
   meet the other chunks by digest.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, forget, laid

LENGTH = 200
GRAM = 32
#: Contexts of one anchor that are sorted together; more are dealt over chunks.
CHUNK_CONTEXTS = 1_000
#: Bytes that one suffix array covers.
SORT_BYTES = 300_000
#: Windows whose digests one task compares between chunks.
SEGMENT_WINDOWS = 500_000
#: Bits of the filter that keeps unique anchors away from the join: 8 a key within these limits.
FILTER_BITS = (1 << 20, 1 << 28)
LAID_BYTES = 500_000
#: A context with more than this fraction of all hits counts as hot and is dealt over as many parts.
HOT = 256
#: Keys that one task puts into the filter, where there are fewer than 256 tasks' worth.
SEGMENT_KEYS = 1_000_000

_B = np.uint64(0x9E3779B97F4A7C15)


def _gram_hashes(b: np.ndarray) -> np.ndarray:
    """Hash of the GRAM bytes from each place, by doubling."""
    h = b.astype(np.uint64) + np.uint64(1)
    width, power = 1, _B
    with np.errstate(over="ignore"):
        while width < GRAM:
            h = h[:-width] * power + h[width:]
            power = power * power
            width *= 2
        h ^= h >> np.uint64(31)
        h *= np.uint64(0xD6E8FEB86659FD93)
        h ^= h >> np.uint64(29)
    return h


def _rightmost_min(h: np.ndarray, span: int) -> np.ndarray:
    """Place of the rightmost smallest value in each stretch of `span` places."""
    value, place, width = h, np.arange(len(h), dtype=np.int32), 1
    while width * 2 <= span:
        right = value[width:] <= value[:-width]
        place = np.where(right, place[width:], place[:-width])
        value = np.where(right, value[width:], value[:-width])
        width *= 2
    if width < span:
        shift = span - width
        right = value[shift:] <= value[:-shift]
        place = np.where(right, place[shift:], place[:-shift])
    return place


def anchors(raws: list[bytes], length: int = LENGTH):
    """(document, anchor hash, first window, windows, context hash) of every run, as arrays."""
    data = b"".join(raws)
    empty = (np.empty(0, np.int64),) * 5
    if len(data) < length:
        return empty
    ends = np.cumsum([len(r) for r in raws])
    b = np.frombuffer(data, np.uint8)
    h = _gram_hashes(b)
    place = _rightmost_min(h, length - GRAM + 1)
    windows = np.arange(len(place))
    doc = np.searchsorted(ends, windows, side="right")
    inside = windows + length <= ends[doc]
    start = inside.copy()
    start[1:] &= (place[1:] != place[:-1]) | ~inside[:-1] | (doc[1:] != doc[:-1])
    first = np.nonzero(start)[0]
    if not len(first):
        return empty
    stop = inside.copy()
    stop[:-1] &= start[1:] | ~inside[1:]
    last = np.nonzero(stop)[0]
    digest = xxhash.xxh3_64_intdigest
    context = np.fromiter((digest(data[s:e]) for s, e in zip(first.tolist(), (last + length).tolist(), strict=True)),
                          np.uint64, len(first))
    d = doc[first]
    begin = ends - [len(r) for r in raws]
    return d, h[place[first]].view(np.int64), first - begin[d], last - first + 1, context.view(np.int64)


def _laid(batches, column: int):
    for batch in batches:
        yield from laid(batch, column, LAID_BYTES)


def _keys(raws: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(xxhash.xxh3_128_digest(r) for r in raws), np.int64).reshape(-1, 2)


def _raw(texts: list[str | None]) -> list[bytes]:
    return [(t or "").encode("utf-8", "surrogatepass") for t in texts]


def _anchor_rows(length: int):
    def run(batches):
        for part in _laid(batches, 0):
            raws = _raw(part.column(0).to_pylist())
            doc, h, first, count, context = anchors(raws, length)
            key = _keys(raws)
            yield pa.RecordBatch.from_arrays(
                [pa.array(h), pa.array(context), pa.array(key[doc, 0] if len(doc) else doc),
                 pa.array(key[doc, 1] if len(doc) else doc), pa.array(first * 1024 + count)],
                names=["h", "ctx", "d1", "d2", "run"])

    return run


class KeyFilter:
    """One-hash Bloom filter over 64-bit keys in 256 segments: may let others through, never stops a member."""

    def __init__(self, bits: int, cells: np.ndarray | None):
        self.bits, self.cells = bits, cells

    @staticmethod
    def inner(keys: np.ndarray, bits: int) -> np.ndarray:
        """Place of a key inside its segment, which its lowest byte names."""
        with np.errstate(over="ignore"):
            return (keys.view(np.uint64) * _B) >> np.uint64(64 - (bits.bit_length() - 1) + 8)

    def holds(self, keys: np.ndarray) -> np.ndarray:
        if self.cells is None:
            return np.ones(len(keys), bool)
        keys = np.ascontiguousarray(keys)
        at = (keys.view(np.uint64) & np.uint64(255)) * np.uint64(self.bits // 256) + self.inner(keys, self.bits)
        return (self.cells[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & np.uint8(1) > 0


def key_filter(keys: DataFrame, column: str, n: int) -> KeyFilter:
    """Built by the executors, each segment in one task, so FILTER_BITS[1] bits at most reach the driver in all.

    Keys that would fill such a filter get none: all of them then go through the join that follows.
    """
    bits = FILTER_BITS[0]
    while bits < min(8 * n, FILTER_BITS[1]):
        bits *= 2
    if 2 * n > bits:
        return KeyFilter(bits, None)
    size = bits // 256 // 8

    def run(batches):
        own: dict[int, np.ndarray] = {}
        for batch in batches:
            k = np.ascontiguousarray(batch.column(0).to_numpy())
            segment = k & 255
            inner = KeyFilter.inner(k, bits)
            for s in np.unique(segment).tolist():
                cells = own.setdefault(s, np.zeros(size, np.uint8))
                at = inner[segment == s]
                np.bitwise_or.at(cells, (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        for s, cells in own.items():
            yield pa.RecordBatch.from_arrays([pa.array([s]), pa.array([cells.tobytes()], pa.binary())],
                                             names=["segment", "cells"])

    named = keys.select(F.col(column).alias("k")).where("k is not null")
    parts = named.repartition(max(1, min(256, -(-n // SEGMENT_KEYS))), F.col("k").bitwiseAND(F.lit(255))).mapInArrow(
        run, "segment long, cells binary")
    cells = np.zeros(bits // 8, np.uint8)
    for row in parts.toLocalIterator():
        lo = row["segment"] * size
        cells[lo:lo + size] |= np.frombuffer(row["cells"], np.uint8)
    return KeyFilter(bits, cells)


def two_stage_order(data: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes of data in order of their first `depth` bytes (the end of data counts as smallest).

    Suffixes that are smaller than their successors are sorted directly. Scanning the order from
    left to right, each suffix then puts its predecessor, when that one is larger than it, at the
    next place of its first byte's bucket.
    """
    n = len(data)
    if n == 0:
        return np.empty(0, np.int64)
    step = np.sign(np.diff(data.astype(np.int16)))
    # equal neighbours take the type of what follows; the last suffix is larger than the empty one
    known = np.append(step, -1)
    at = np.where(known != 0, np.arange(n), n - 1)
    following = np.minimum.accumulate(at[::-1])[::-1]
    smaller = known[following] > 0
    direct = np.nonzero(smaller)[0]
    padded = np.concatenate([data, np.zeros(depth, np.uint8)])
    rows = np.lib.stride_tricks.sliding_window_view(padded, depth)[direct]
    by_bytes = np.argsort(np.ascontiguousarray(rows).view(f"S{depth}").ravel(), kind="stable") if len(direct) else direct
    direct = direct[by_bytes]
    counts = np.bincount(data, minlength=256)
    head = np.concatenate([[0], np.cumsum(counts)[:-1]])
    order = np.full(n, -1, np.int64)
    # in a bucket the induced suffixes come first, the directly sorted ones last
    first_of = data[direct]
    own = np.bincount(first_of, minlength=256)
    tail = head + counts - own
    inner = np.arange(len(direct)) - np.concatenate([[0], np.cumsum(own)[:-1]])[first_of]
    order[tail[first_of] + inner] = direct
    out, heads, bytes_, small = order.tolist(), head.tolist(), data.tolist(), smaller.tolist()
    c = bytes_[n - 1]
    out[heads[c]] = n - 1  # it follows the empty suffix
    heads[c] += 1
    j = 0
    while j < n:
        i = out[j] - 1
        if i >= 0 and not small[i]:
            c = bytes_[i]
            out[heads[c]] = i
            heads[c] += 1
        j += 1
    return np.array(out, np.int64)


def repeated_windows(contexts: list[bytes], counts: list[int], length: int = LENGTH):
    """Which of the first counts[i] windows of each context occur again among all of them.

    Gives (flags, leader): flags[i] is a boolean array over the windows of context i; leader marks
    one window of each set of equal ones, which stands for the set towards other chunks.
    """
    data = np.frombuffer(b"".join(contexts), np.uint8)
    sizes = np.array([len(c) for c in contexts])
    begin = np.cumsum(sizes) - sizes
    n = len(data)
    wanted = np.zeros(n, bool)
    for s, c in zip(begin.tolist(), counts, strict=True):
        wanted[s:s + c] = True
    order = two_stage_order(data, length)
    order = order[wanted[order]]  # the windows asked for, still in order
    hit = np.zeros(n, bool)
    leader = np.zeros(n, bool)
    if len(order):
        rows = np.lib.stride_tricks.sliding_window_view(data, length)
        same = np.zeros(len(order), bool)  # common prefix with the one before covers the window
        for lo in range(1, len(order), 50_000):
            a, b = order[lo - 1:lo + 49_999], order[lo:lo + 50_000]
            same[lo:lo + 50_000] = (rows[a[:len(b)]] == rows[b]).all(axis=1)
        again = same.copy()
        again[:-1] |= same[1:]
        hit[order] = again
        leader[order] = ~same
    return [hit[s:s + c] for s, c in zip(begin, counts, strict=True)], [leader[s:s + c] for s, c in zip(begin, counts, strict=True)]


def _spans(flags: np.ndarray) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    return list(zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True))


def _sort_contexts(length: int, segments: int):
    """Spans found in a chunk; for anchors of several chunks also what the others have to know,
    packed by digest segment: two words of digest, two of the text's key, and place * 2 + undecided."""
    names = ["d1", "d2", "lo", "hi", "segment", "packed"]

    def run(batches):
        held: list[tuple] = []
        packed: list[np.ndarray] = []

        def send():
            rows = np.concatenate(packed)
            packed.clear()
            at = rows[:, 0].view(np.uint64) % np.uint64(segments)
            order = np.argsort(at, kind="stable")
            present, first = np.unique(at[order], return_index=True)
            parts = [p.tobytes() for p in np.split(rows[order], first[1:])]
            none = pa.nulls(len(parts), pa.int64())
            return pa.RecordBatch.from_arrays([none, none, none, none, pa.array(present.astype(np.int64)), pa.array(parts, pa.binary())],
                                              names=names)

        def done():
            flags, leaders = repeated_windows([r[4] for r in held], [r[3] % 1024 for r in held], length)
            out: list[list] = [[], [], [], []]
            for r, hit, lead in zip(held, flags, leaders, strict=True):
                ws = r[3] // 1024
                for lo, hi in _spans(hit):
                    for column, value in zip(out, (r[1], r[2], ws + lo, ws + hi - 1 + length), strict=True):
                        column.append(value)
                if r[0] > 1:
                    at = np.nonzero(lead)[0]
                    digest = b"".join(xxhash.xxh3_128_digest(r[4][i:i + length]) for i in at.tolist())
                    packed.append(np.column_stack([np.frombuffer(digest, np.int64).reshape(-1, 2), np.full(len(at), r[1]),
                                                   np.full(len(at), r[2]), 2 * (ws + at) + ~hit[at]]).astype(np.int64))
            held.clear()
            return pa.RecordBatch.from_arrays([*[pa.array(c, pa.int64()) for c in out], pa.nulls(len(out[0]), pa.int64()),
                                               pa.nulls(len(out[0]), pa.binary())], names=names)

        size, last = 0, None
        for batch in batches:
            for r in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                # one anchor and chunk stays together: (h, chunk) sorts the rows of a partition
                if held and (r[0], r[1]) != last and size >= SORT_BYTES:
                    yield done()
                    size = 0
                    if sum(map(len, packed)) > 400_000:
                        yield send()
                last = (r[0], r[1])
                held.append((r[2], r[3], r[4], r[5], r[6]))
                size += len(r[6])
        if held:
            yield done()
        if packed:
            yield send()

    return run


def _between_chunks(length: int):
    """Undecided windows that another chunk holds as well; a chunk sends each window once."""
    def run(table: pa.Table) -> pa.Table:
        rows = np.concatenate([np.frombuffer(p.as_py(), np.int64).reshape(-1, 5) for p in table["packed"]])
        rows = rows[np.lexsort((rows[:, 1], rows[:, 0]))]
        same = (rows[1:, :2] == rows[:-1, :2]).all(axis=1)
        again = np.concatenate([[False], same]) | np.concatenate([same, [False]])
        rows = rows[again & (rows[:, 4] & 1 == 1)]
        lo = rows[:, 4] >> 1
        return pa.table({"d1": rows[:, 2], "d2": rows[:, 3], "lo": lo, "hi": lo + length})

    return run


def _repeated(hits: DataFrame, kinds: DataFrame) -> DataFrame:
    """(d1, d2, run) of the hits whose context occurs more than once.

    A context that holds more than a HOT-th of all hits is dealt over that many salts; there are fewer than
    HOT such contexts, whatever the data, so their list can be broadcast.
    """
    total = kinds.agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0]
    hot = F.broadcast(kinds.where(F.col("c") * HOT > total).select("h", "ctx", F.lit(HOT).alias("salts")))
    salts = F.coalesce("salts", F.lit(1))
    dealt = hits.join(hot, ["h", "ctx"], "left").withColumn("salt", F.pmod(F.xxhash64("d1", "d2", "run"), salts).cast("int"))
    asked = kinds.select("h", "ctx").join(hot, ["h", "ctx"], "left").select(
        "h", "ctx", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
    return dealt.join(asked, ["h", "ctx", "salt"], "left_semi").select("d1", "d2", "run")


def remove_repeats(docs: DataFrame, length: int = LENGTH, id_column: str = "doc_id", text_column: str = "text",
                   keep_text: bool = False, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256[, kept_text][, carried]), one row for each input row.

    Bytes covered by a string of `length` bytes that starts anywhere else as well are removed, in
    every place where it occurs. Null texts count as empty. Texts shorter than `length` lose
    nothing; repeated rows and copies lose all of it. Null ids pass through; an empty table gives no
    rows; only the two named columns and those to carry are read (the latter come back as the fields
    of `carried`). A cut may split a character: kept_text leaves out its remaining bytes.
    """
    if not GRAM < length <= 1023 - GRAM:
        raise ValueError(f"length must lie between {GRAM} and {1023 - GRAM} bytes")
    along = F.struct(*[F.col(c) for c in carry]) if carry else F.lit(None).cast("struct<none:int>")
    named = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).cast("string").alias("text"),
                        along.alias("carried"))
    carried = named.schema["carried"].dataType.simpleString()
    rows = cut(named.select("text").mapInArrow(_anchor_rows(length), "h long, ctx long, d1 long, d2 long, run long"), "suffix-anchors")
    shared = cut(rows.groupBy("h").agg(F.count("*").alias("c"), (F.min("ctx") != F.max("ctx")).alias("mixed")).where("c > 1")
                 .select("h", "mixed"), "suffix-shared")
    context = docs.sparkSession.sparkContext
    known = context.broadcast(key_filter(shared, "h", shared.count()))

    def may_share(batches):
        for batch in batches:
            yield batch.filter(pa.array(known.value.holds(batch.column(0).to_numpy())))

    hits = cut(rows.mapInArrow(may_share, rows.schema).join(shared, "h"), "suffix-hits")
    forget(rows)
    # contexts that meet other contexts of their anchor, one of each kind
    kinds = cut(hits.where("mixed").groupBy("h", "ctx").agg(
        F.count("*").alias("c"), F.min(F.struct("d1", "d2", "run")).alias("at")).select("h", "ctx", "c", "at.*"), "suffix-kinds")
    sizes = kinds.groupBy("h").agg(F.ceil(F.count("*") / CHUNK_CONTEXTS).cast("int").alias("chunks"))

    owners = hits.select("d1")
    in_hits = context.broadcast(key_filter(owners, "d1", hits.count()))

    def split(batches):
        for part in _laid(batches, 1):
            texts = part.column(1).to_pylist()
            raws = _raw(texts)
            key = _keys(raws)
            found = in_hits.value.holds(key[:, 0]) if len(raws) else []
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array([len(r) for r in raws], pa.int64()), pa.array(key[:, 0]), pa.array(key[:, 1]),
                 pa.array([t if f or keep_text else None for t, f in zip(texts, found, strict=True)], pa.string()),
                 pa.array([None if f else hashlib.sha256(r).hexdigest() for r, f in zip(raws, found, strict=True)], pa.string()),
                 part.column(2)],
                names=["doc_id", "n_bytes", "d1", "d2", "text", "sha", "carried"])

    laid = cut(named.mapInArrow(
        split, f"doc_id long, n_bytes long, d1 long, d2 long, text string, sha string, carried {carried}"), "suffix-docs")
    touched = laid.where("sha is null")

    asked = kinds.join(sizes, "h").select("h", (F.abs(F.col("ctx") % F.col("chunks"))).alias("chunk"), "chunks", "d1", "d2", "run")
    per_doc = asked.groupBy("d1", "d2").agg(F.collect_list(F.struct("h", "chunk", "chunks", "run")).alias("asked"))

    def contexts_of(batches):
        names = ["h", "chunk", "chunks", "d1", "d2", "run", "ctx"]
        for batch in batches:
            out: list[tuple] = []
            for d1, d2, text, wanted in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                raw = text.encode("utf-8", "surrogatepass")
                for w in wanted:
                    ws, count = divmod(w["run"], 1024)
                    out.append((w["h"], w["chunk"], w["chunks"], d1, d2, w["run"], raw[ws:ws + count - 1 + length]))
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[i] for r in out], pa.binary() if i == 6 else pa.int64()) for i in range(7)], names=names)

    # copies of a text hold the same contexts: one row speaks for them
    one_each = touched.groupBy("d1", "d2").agg(F.first("text").alias("text"))
    bytes_of = one_each.join(per_doc, ["d1", "d2"]).select("d1", "d2", "text", "asked").mapInArrow(
        contexts_of, "h long, chunk long, chunks long, d1 long, d2 long, run long, ctx binary")
    dealt = bytes_of.repartition(F.col("h"), F.col("chunk")).sortWithinPartitions("h", "chunk").select(
        "h", "chunk", "chunks", "d1", "d2", "run", "ctx")
    # digests that chunks exchange: some 85 windows a context, in segments a task can hold
    exchanged = sizes.where("chunks > 1").agg(F.coalesce(F.sum("chunks"), F.lit(0))).first()[0] * CHUNK_CONTEXTS
    segments = max(1, -(-exchanged * 85 // SEGMENT_WINDOWS))
    sorted_ = cut(dealt.mapInArrow(_sort_contexts(length, segments),
                                   "d1 long, d2 long, lo long, hi long, segment long, packed binary"), "suffix-sorted")
    across = sorted_.where("segment is not null").select("segment", "packed").groupBy("segment").applyInArrow(
        _between_chunks(length), "d1 long, d2 long, lo long, hi long")
    whole = hits.where("not mixed").select("d1", "d2", "run").unionByName(_repeated(hits.where("mixed"), kinds.where("c > 1")))
    first = F.floor(F.col("run") / 1024)
    spans = (whole.select("d1", "d2", first.alias("lo"), (first + F.col("run") % 1024 - 1 + length).alias("hi"))
             .unionByName(sorted_.where("segment is null").select("d1", "d2", "lo", "hi")).unionByName(across).distinct())
    by_doc = spans.groupBy("d1", "d2").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))

    def apply(batches):
        for batch in batches:
            columns: list[list] = [[] for _ in range(4)]
            for text, spans in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                raw = (text or "").encode("utf-8", "surrogatepass")
                kept, at, removed, n = [], 0, 0, 0
                for lo, hi in sorted((s["lo"], s["hi"]) for s in spans or ()):
                    if hi <= at and n:
                        continue
                    if n and lo <= at:
                        removed += hi - at
                    else:
                        kept.append(raw[at:lo])
                        removed += hi - lo
                        n += 1
                    at = hi
                kept.append(raw[at:])
                left = b"".join(kept)
                columns[0].append(removed)
                columns[1].append(n)
                columns[2].append(hashlib.sha256(left).hexdigest())
                columns[3].append(left.decode("utf-8", "ignore") if keep_text else None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()),
                 pa.array(columns[2], pa.string()), pa.array(columns[3], pa.string()), batch.column(4)],
                names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text", "carried"])

    done = touched.join(by_doc, ["d1", "d2"], "left").select("doc_id", "n_bytes", "text", "spans", "carried").mapInArrow(
        apply, f"doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept_text string, carried {carried}")
    clean = laid.where("sha is not null").select("doc_id", "n_bytes", F.lit(0).cast("long").alias("n_removed"),
                                                 F.lit(0).cast("long").alias("n_spans"), F.col("sha").alias("kept_sha256"),
                                                 F.col("text").alias("kept_text"), "carried")
    out = done.unionByName(clean)
    return out.drop(*([] if keep_text else ["kept_text"]), *([] if carry else ["carried"]))
