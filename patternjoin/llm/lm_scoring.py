"""Language-model scores: a small causal self-attention model in numpy, and a unigram base.

Texts become subword ids: pieces of a public rank file, merged further and thinned out by their
counts in all training texts, so that as many ids spell longer pieces. Every text is encoded once. A text is laid out in blocks; the
window of a block is the block and the one before, so windows overlap by half and every id is
scored exactly once, with batched attention under a causal mask. The next id is predicted digit
by digit (three digits to the base 16), which keeps the output layer small.

The model is fitted in one pass over all training texts, by rounds of local training: a text falls
in one of the rounds, every replica trains on its share of the round's texts, and the replicas'
parameters are averaged level by level. Word counts for the base cover all training texts too.
"""

from __future__ import annotations

import ctypes
import math
import re
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .byte_bpe import read_ranks
from .common import cut, forget, laid
from .words import word_digests

BASE = 16
VOCABULARY = BASE**3  # ranks 0 .. VOCABULARY - 2, and the end of a text
END, START, PAD = VOCABULARY - 1, VOCABULARY, VOCABULARY + 1
SPLIT = r"\s?\S+|\s+"
_PIECES = re.compile(SPLIT)
WIDTH, HIDDEN, BLOCK = 16, 32, 16
LIMIT = 30.0
#: Blocks that one step of scoring takes.
STRETCH = 400
#: Texts a replica trains on in a round, rounds of averaging, and sets of parameters that one task averages.
REPLICA_DOCS, ROUNDS, FAN_IN = 4_000, 3, 32
#: Rounds of merging, and the fewest occurrences of a merged pair.
MERGE_ROUNDS, FEWEST = 6, 20
#: Different pieces of text that a task counts, or spells, at once.
PIECES_HELD = 200_000
#: Characters of text that are laid out at once; a longer text is taken alone.
LAID_CHARS = 300_000
#: Words whose counts every executor holds; the others are counted by a join.
FREQUENT_WORDS = 500_000

Params = dict[str, np.ndarray]


@lru_cache(maxsize=2)
def public_vocabulary(path: str) -> tuple[bytes, ...]:
    return tuple(sorted((t for t, r in read_ranks(path).items() if r < END), key=read_ranks(path).__getitem__))


@lru_cache(maxsize=2)
def _encoding(vocabulary: tuple[bytes, ...]) -> tiktoken.Encoding:
    return tiktoken.Encoding("subwords", pat_str=SPLIT, mergeable_ranks={t: r for r, t in enumerate(vocabulary)}, special_tokens={})


def subword_ids(texts: list[str], path: str, vocabulary: tuple[bytes, ...] | None = None) -> list[np.ndarray]:
    encode = _encoding(vocabulary or public_vocabulary(path)).encode_ordinary
    return [np.array(encode(t), np.int32) for t in texts]


def piece_counts(texts: DataFrame) -> DataFrame:
    """(piece, c): the stretches of SPLIT in every text, none left out, and how often each occurs."""
    def run(batches):
        held: Counter[str] = Counter()
        for batch in batches:
            for cell in batch.column(0):
                t = cell.as_py() or ""
                held.update(_PIECES.findall(t) if len(t) < LAID_CHARS else (m.group() for m in _PIECES.finditer(t)))
                if len(held) > PIECES_HELD:
                    yield pa.RecordBatch.from_arrays([pa.array(held.keys(), pa.string()), pa.array(held.values(), pa.int64())], names=["piece", "c"])
                    held.clear()
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(held.keys(), pa.string()), pa.array(held.values(), pa.int64())], names=["piece", "c"])

    return texts.select("text").mapInArrow(run, "piece string, c long").groupBy("piece").agg(F.sum("c").alias("c"))


def _uses(pieces: list[str], times: np.ndarray, path: str, tokens: tuple[bytes, ...]) -> tuple[np.ndarray, np.ndarray]:
    """(what, occurrences) over pieces that come so many times: ids, as -1 - id, and pairs of neighbouring ids that may be
    merged, as left * len(tokens) + right. Pieces of a text begin with white space, so no pair whose second half does."""
    n = len(tokens)
    ids = subword_ids(pieces, path, tokens)
    size = np.array([len(i) for i in ids], np.int64)
    flat = np.concatenate([np.empty(0, np.int64), *ids])
    of = np.repeat(times, size)
    inner = np.ones(len(flat), bool)
    inner[np.cumsum(size)[size > 0] - 1] = False
    at = np.flatnonzero(inner)
    pair, place = np.unique(flat[at] * n + flat[at + 1], return_inverse=True)
    known = set(tokens)
    free = np.array([not tokens[r][:1].isspace() and tokens[l] + tokens[r] not in known for l, r in zip(*(x.tolist() for x in np.divmod(pair, n)), strict=True)], bool)
    one, where = np.unique(flat, return_inverse=True)
    # whole numbers below 2^53 are exact as weights
    single, double = np.bincount(where, of, len(one)).astype(np.int64), np.bincount(place, of[at], len(pair)).astype(np.int64)
    return np.concatenate([-1 - one, pair[free]]), np.concatenate([single, double[free]])


def _merged(uses, path: str) -> tuple[bytes, ...]:
    """In each round the most frequent pairs of ids become pieces and those used least make room; `uses` gives the counts under
    some tokens: all of the ids', and those of the most frequent pairs."""
    tokens = list(public_vocabulary(path))
    for _ in range(MERGE_ROUNDS):
        what, n = uses(tuple(tokens))
        count = np.zeros(len(tokens), np.int64)
        count[-1 - what[what < 0]] = n[what < 0]
        pair, n = what[what >= 0], n[what >= 0]
        known, new = set(tokens), []
        for k in np.lexsort((pair, -n)):
            if n[k] < FEWEST or len(new) == END // 6:
                break
            left, right = tokens[pair[k] // len(tokens)], tokens[pair[k] % len(tokens)]
            if left + right not in known:
                new.append(left + right)
                known.add(left + right)
        used = [(t, c) for t, c in zip(tokens, count.tolist(), strict=True) if c or len(t) == 1]
        spare = sorted((t for t, c in used if len(t) > 1), key=dict(used).__getitem__)
        dropped = set(spare[:max(0, len(used) + len(new) - END)])
        tokens = [t for t, _ in used if t not in dropped] + new
    return tuple(tokens)


def merged_vocabulary(texts: list[str], path: str) -> tuple[bytes, ...]:
    """All bytes and the pieces that serve these texts best. Without texts it is the public one."""
    held = Counter(piece for t in texts for piece in _PIECES.findall(t))
    if not held:
        return public_vocabulary(path)
    return _merged(lambda tokens: _uses(list(held), np.array(list(held.values()), np.int64), path, tokens), path)


def fit_vocabulary(texts: DataFrame, rank_file: str, n: int) -> tuple[bytes, ...]:
    """The vocabulary of n training rows with a column `text`: merged by counts over all of their characters.

    Pieces are counted once; a round of merging spells each different piece once, and the driver gets the counts of
    the ids and of the pairs that can be among the merged ones.
    """
    pieces = cut(piece_counts(texts), "lm-pieces") if n else None
    if pieces is None or pieces.isEmpty():
        return public_vocabulary(rank_file)

    def uses(tokens: tuple[bytes, ...]) -> tuple[np.ndarray, np.ndarray]:
        def run(batches):
            for batch in batches:
                for lo in range(0, batch.num_rows, PIECES_HELD):
                    part = batch.slice(lo, PIECES_HELD)
                    what, c = _uses(part.column(0).to_pylist(), part.column(1).to_numpy(), rank_file, tokens)
                    yield pa.RecordBatch.from_arrays([pa.array(what, pa.int64()), pa.array(c, pa.int64())], names=["what", "c"])

        summed = pieces.mapInArrow(run, "what long, c long").groupBy("what").agg(F.sum("c").alias("c"))
        # two pairs can spell the same piece: more than a round takes
        best = summed.orderBy(F.col("what") >= 0, F.col("c").desc(), "what").limit(END + 4 * (END // 6)).toArrow()
        return best["what"].to_numpy(), best["c"].to_numpy()

    found = _merged(uses, rank_file)
    forget(pieces)
    return found


def encode_texts(rows: DataFrame, rank_file: str, vocabulary: tuple[bytes, ...] | None = None) -> DataFrame:
    """The rows with their texts' ids as 16-bit numbers, written once."""
    def run(batches):
        for batch in batches:
            at = batch.schema.get_field_index("text")
            for part in laid(batch, at, LAID_CHARS):
                ids = subword_ids([t or "" for t in part.column(at).to_pylist()], rank_file, vocabulary)
                coded = pa.array([i.astype("<u2").tobytes() for i in ids], pa.binary())
                yield pa.RecordBatch.from_arrays([*part.columns, coded], names=[*part.schema.names, "ids"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema)
    return cut(rows.mapInArrow(run, schema + ", ids binary"), "lm-ids")


def _ids(column: pa.Array) -> list[np.ndarray]:
    return [np.frombuffer(b, "<u2").astype(np.int32) for b in column.to_pylist()]


def initial(seed: int = 7) -> Params:
    """A is the product of the query and key projections, O that of value and output: heads are as wide as the model."""
    g = np.random.default_rng(seed)
    d = WIDTH
    new = lambda *shape, scale=None: (g.standard_normal(shape) * (scale or shape[0] ** -0.5)).astype(np.float32)
    p = {"E": new(PAD + 1, d, scale=0.3), "A": new(d, d), "O": new(d, d, scale=0.1),
         "R": np.zeros((BLOCK, 2 * BLOCK), np.float32), "F1": new(d, HIDDEN), "f": np.zeros(HIDDEN, np.float32),
         "F2": new(HIDDEN, d, scale=0.1), "W": new(d, 3 * BASE, scale=0.1), "b1": np.zeros(BASE, np.float32),
         "b2": np.zeros((BASE, BASE), np.float32), "b3": np.zeros((BASE * BASE, BASE), np.float32)}
    p["E"][PAD] = 0
    return p


@lru_cache(maxsize=1)
def keep_memory() -> None:
    """Freed arrays stay with the process: else each step gives its pages back and has them zeroed again, a quarter of its time."""
    try:
        mallopt = ctypes.CDLL(None).mallopt
    except (AttributeError, OSError):  # another C library
        return
    mallopt(-3, 1 << 26)  # M_MMAP_THRESHOLD
    mallopt(-1, 1 << 27)  # M_TRIM_THRESHOLD


#: Sums over each digit's logits, by a product.
_DIGITS = np.kron(np.eye(3, dtype=np.float32), np.ones((BASE, 1), np.float32))
_PAST = np.tril(np.ones((BLOCK, 2 * BLOCK), np.float32), BLOCK)


def lay_out(ids: list[np.ndarray]):
    """(inputs, targets, first target of each text): blocks of all texts, a block of padding before each.

    Unused targets are -1; the places of a text's targets are contiguous within its blocks.
    """
    n = np.array([len(i) + 1 for i in ids])
    blocks = 1 + -(-n // BLOCK)
    start = (np.cumsum(blocks) - blocks + 1) * BLOCK
    x = np.full(int(blocks.sum()) * BLOCK, PAD, np.int32)
    y = np.full(len(x), -1, np.int32)
    flat = np.concatenate([np.asarray(i, np.int32) for i in ids])
    at = np.arange(len(flat)) + np.repeat(start - (np.cumsum(n - 1) - (n - 1)), n - 1)
    y[at] = flat
    y[start + n - 1] = END
    x[at + 1] = flat  # the last id is the input that predicts the end
    x[start] = START
    return x.reshape(-1, BLOCK), y.reshape(-1, BLOCK), start, n


def _windows(rows: np.ndarray) -> np.ndarray:
    """Each block behind the one before it: overlapping views of the rows, not copies."""
    step, item = rows.strides
    return np.lib.stride_tricks.as_strided(rows, (len(rows) // BLOCK - 1, 2 * BLOCK, rows.shape[1]), (BLOCK * step, step, item))


class Scorer:
    """The forward pass alone, with everything that depends on one id folded into tables.

    A column of ones beside the values gives the attention's denominators, and padding has
    zeros there, which masks it.
    """

    def __init__(self, p: Params):
        scale = np.float32(WIDTH**-0.5)
        e, d = p["E"], WIDTH
        self.table = np.concatenate([e, e @ (p["A"] * scale), e @ p["O"], np.ones((len(e), 1), np.float32)], axis=1)
        self.table[PAD] = 0
        self.p = p
        top = np.repeat(p["b2"], BASE, axis=0)
        self.bias = np.concatenate([np.broadcast_to(p["b1"], (BASE * BASE, BASE)), top, p["b3"]], axis=1).astype(np.float32)

    def logp(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Natural log probabilities of the targets y >= 0 of all blocks but the first."""
        p, d, nb = self.p, WIDTH, len(x)
        rows = self.table.take(x.ravel(), axis=0)
        window = _windows(rows)
        h = rows.reshape(nb, BLOCK, -1)[1:]
        s = h[..., d:2 * d] @ window[..., :d].transpose(0, 2, 1)
        s += p["R"]
        np.clip(s, -LIMIT, LIMIT, out=s)
        np.exp(s, out=s)
        s *= _PAST
        mixed = s @ window[..., 2 * d:]
        o = mixed[..., :d]
        o /= mixed[..., d:] + np.float32(1e-9)
        o += h[..., :d]
        o, t = o.reshape(-1, d), y[1:].ravel()
        live = t >= 0
        t = np.maximum(t, 0)  # few places have no target: they are left out at the end
        f = o @ p["F1"]
        f += p["f"]
        np.maximum(f, 0, out=f)
        o += f @ p["F2"]
        logits = o @ p["W"]
        high = t >> 4
        logits += self.bias.take(high, axis=0)
        np.clip(logits, -LIMIT, LIMIT, out=logits)
        at = np.arange(0, logits.size, 3 * BASE)
        flat = logits.ravel()
        chosen = flat.take(at + (t >> 8)) + flat.take(at + (BASE + (high & 15))) + flat.take(at + (2 * BASE + (t & 15)))
        np.exp(logits, out=logits)
        total = logits @ _DIGITS
        chosen -= np.log(total) @ np.ones(3, np.float32)
        return chosen[live]


def text_logp(p: Params | Scorer, ids: list[np.ndarray]) -> np.ndarray:
    """Natural log probability of each text, its end included."""
    scorer = p if isinstance(p, Scorer) else Scorer(p)
    out = np.zeros(len(ids))
    lo, held = 0, 0
    for i, t in enumerate(ids):
        held += len(t) + 2 * BLOCK
        if held > 5_000 or i == len(ids) - 1:
            x, y, _, n = lay_out(ids[lo:i + 1])
            # stretches small enough for the processor's cache; a long text is taken in several,
            # each beside the last block of the one before
            done = [scorer.logp(x[part:part + STRETCH + 1], y[part:part + STRETCH + 1]).astype(np.float64)
                    for part in range(0, len(x) - 1, STRETCH)]
            out[lo:i + 1] = np.add.reduceat(np.concatenate(done), np.cumsum(n) - n)
            lo, held = i + 1, 0
    return out


def _gradients(p: Params, x: np.ndarray, y: np.ndarray) -> tuple[float, Params]:
    """Mean loss over the targets of all blocks but the first, and its gradients."""
    d, nb, ids = WIDTH, len(x), x.ravel()
    t = y[1:].ravel()
    # places in the order of their targets, unused ones (65,535 as 16 bits) left out: sums by target need no gathering
    live = np.argsort(t.astype(np.uint16), kind="stable")[:np.count_nonzero(t >= 0)]
    t = t[live]
    n = len(t)
    ask = p["A"] * np.float32(d**-0.5)
    # a column of ones beside the values gives the denominators; padding has zeros, which masks it
    rows = np.concatenate([p["E"], np.ones((PAD + 1, 1), np.float32)], axis=1)
    rows[PAD] = 0
    rows = rows.take(ids, axis=0)
    window = _windows(rows)
    keys, h = window[..., :d], rows[BLOCK:, :d]
    q = (h @ ask).reshape(nb - 1, BLOCK, d)
    s = q @ keys.transpose(0, 2, 1)
    s += p["R"]
    np.clip(s, -LIMIT, LIMIT, out=s)
    np.exp(s, out=s)
    s *= _PAST
    mixed = (s @ window).reshape(-1, d + 1)
    below = 1 / (mixed[:, d:] + np.float32(1e-9))
    mixed = mixed[:, :d] * below
    o = mixed @ p["O"]
    o += h
    o = o.take(live, axis=0)
    f = o @ p["F1"]
    f += p["f"]
    np.maximum(f, 0, out=f)
    z = f @ p["F2"]
    z += o
    high = t >> 4
    dl = z @ p["W"]
    bias = np.concatenate([np.broadcast_to(p["b1"], (BASE * BASE, BASE)), np.repeat(p["b2"], BASE, axis=0), p["b3"]], axis=1)
    dl += bias.take(high, axis=0)
    np.clip(dl, -LIMIT, LIMIT, out=dl)
    flat, at = dl.reshape(-1), np.arange(0, dl.size, 3 * BASE)
    digits = np.concatenate([at + (t >> 8), at + (BASE + (high & 15)), at + (2 * BASE + (t & 15))])
    chosen = flat.take(digits).sum(dtype=np.float64)
    np.exp(dl, out=dl)
    total = dl @ _DIGITS
    loss = float((np.log(total).sum(dtype=np.float64) - chosen) / n)
    dl *= (np.float32(1 / n) / total) @ _DIGITS.T
    flat[digits] -= np.float32(1 / n)
    g: Params = {"W": z.T @ dl, "b1": np.ones(n, np.float32) @ dl[:, :BASE], "b2": _runs(t >> 8, dl[:, BASE:2 * BASE], BASE),
                 "b3": _runs(high, dl[:, 2 * BASE:], BASE * BASE)}
    dz = dl @ p["W"].T
    g["F2"] = f.T @ dz
    df = dz @ p["F2"].T
    df *= f > 0
    g["F1"], g["f"] = o.T @ df, np.ones(n, np.float32) @ df
    dz += df @ p["F1"].T
    do = np.zeros((len(h), d), np.float32)
    do[live] = dz
    g["O"] = mixed.T @ do
    dm = np.empty((len(h), d + 1), np.float32)
    np.multiply(do @ p["O"].T, below, out=dm[:, :d])
    np.negative(np.einsum("ij,ij->i", dm[:, :d], mixed), out=dm[:, d])
    dm = dm.reshape(nb - 1, BLOCK, d + 1)
    ds = dm @ window.transpose(0, 2, 1)
    ds *= s
    g["R"] = ds.sum(axis=0)
    back = s.transpose(0, 2, 1) @ dm[..., :d]
    back += ds.transpose(0, 2, 1) @ q
    dq = (ds @ keys).reshape(-1, d)
    g["A"] = h.T @ dq * np.float32(d**-0.5)
    do += dq @ ask.T
    dh = np.empty((nb, BLOCK, d), np.float32)
    dh[:-1] = back[:, :BLOCK]
    dh[-1] = 0
    dh[1:] += back[:, BLOCK:]
    dh = dh.reshape(-1, d)
    dh[BLOCK:] += do
    g["E"] = _by_row(ids, dh, PAD + 1)
    g["E"][PAD] = 0
    return loss, g


def _runs(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sums of the values of each of n row numbers, which come sorted."""
    out = np.zeros((n, values.shape[1]), np.float32)
    first = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
    out[rows[first]] = np.add.reduceat(values, first, axis=0)
    return out


def _by_row(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """The same for numbers in any order, which fit 16 bits: those are sorted by radix."""
    small = rows.astype(np.uint16)
    order = np.argsort(small, kind="stable")
    return _runs(small[order], values.take(order, axis=0), n)


class Adam:
    """First and second moments of a replica's gradients, kept over all of its texts.

    They and the parameters lie in one flat array each: p holds views of it from then on.
    """

    def __init__(self, p: Params):
        self.names = list(p)
        self.flat = np.concatenate([p[k].ravel() for k in self.names]).astype(np.float32)
        at = 0
        for k in self.names:
            p[k], at = self.flat[at:at + p[k].size].reshape(p[k].shape), at + p[k].size
        self.m, self.v = np.zeros_like(self.flat), np.zeros_like(self.flat)
        self.steps = 0

    def step(self, p: Params, g: Params, rate: float) -> None:
        self.steps += 1
        n = self.steps
        rate *= min(1.0, n / 20) * math.sqrt(1 - 0.99**n) / (1 - 0.9**n)
        w = np.concatenate([g[k].ravel() for k in self.names])
        self.m *= np.float32(0.9)
        self.m += np.float32(0.1) * w
        w *= w
        w *= np.float32(0.01)
        self.v *= np.float32(0.99)
        self.v += w
        np.sqrt(self.v, out=w)
        w += np.float32(1e-8)
        np.divide(self.m, w, out=w)
        w *= np.float32(rate)
        self.flat -= w


def train_replica(p: Params, ids: list[np.ndarray], rate: float, batch_blocks: int = 192, seed: int = 0, state: Adam | None = None) -> float:
    """One pass over the texts, p is changed in place; gives the mean loss."""
    state = state or Adam(p)
    order = np.random.default_rng(seed).permutation(len(ids))
    loss, steps, group, size = 0.0, 0, [], 0
    for place, i in enumerate(order):
        group.append(ids[i])
        size += len(ids[i]) // BLOCK + 2
        if size < batch_blocks and place < len(order) - 1:
            continue
        x, y, _, _ = lay_out(group)
        for lo in range(0, len(x), 2 * batch_blocks):
            part, target = x[max(0, lo - 1):lo + 2 * batch_blocks], y[max(0, lo - 1):lo + 2 * batch_blocks].copy()
            if lo:
                target[0] = -1
            if not (target >= 0).any():
                continue
            one, g = _gradients(p, part, target)
            steps += 1
            loss += one
            state.step(p, g, rate)
        group, size = [], 0
    return loss / max(1, steps)


def _pack(p: Params) -> bytes:
    return np.concatenate([p[k].ravel() for k in sorted(p)]).astype(np.float32).tobytes()


def _unpack(data: bytes) -> Params:
    flat, at, out = np.frombuffer(data, np.float32), 0, {}
    like = initial()
    for k in sorted(like):
        out[k] = flat[at:at + like[k].size].reshape(like[k].shape).copy()
        at += like[k].size
    return out


def fit_model(texts: DataFrame, rank_file: str, rounds: int = ROUNDS) -> Params:
    """Train on every row of (doc_id, text), in the ids of the public vocabulary."""
    return train_model(encode_texts(texts.select("text", F.xxhash64("doc_id", "text").alias("key")), rank_file), rounds)


def train_model(coded: DataFrame, rounds: int = ROUNDS) -> Params:
    """Train on every row of (key, ids), in one of the rounds."""
    n = coded.count()
    p = initial()
    if n == 0:
        return p
    spark = coded.sparkSession
    replicas = max(1, math.ceil(n / rounds / REPLICA_DOCS))
    for turn in range(rounds):
        now = spark.sparkContext.broadcast(_pack(p))  # some 0.3 MB, whatever the data
        rate = 0.02 * 0.5**turn

        def train(batches, now=now, rate=rate, turn=turn):
            keep_memory()
            own, weight = _unpack(now.value), 0.0
            state = Adam(own)
            for batch in batches:
                for part in laid(batch, 0, LAID_CHARS):
                    ids = _ids(part.column(0))
                    train_replica(own, ids, rate, seed=turn, state=state)
                    weight += sum(map(len, ids)) + len(ids)
            if weight:
                yield pa.RecordBatch.from_arrays(
                    [pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([weight]), pa.array([_pack(own)], pa.binary())],
                    names=["place", "weight", "params"])

        # dealt by id and text, so that neither copies of a text nor of an id gather in one replica
        share = coded.where(F.pmod("key", F.lit(rounds)) == turn).select("ids", "key").repartition(replicas, F.xxhash64("key")).select("ids")
        rows = average(share.mapInArrow(train, "place long, weight double, params binary"), replicas).collect()  # one row at most
        now.unpersist()
        if rows:
            p = _unpack(rows[0]["params"])
    return p


def average(trained: DataFrame, places: int) -> DataFrame:
    """One row of weighted mean parameters: no task holds more than FAN_IN sets, however many replicas there are."""
    def mean(table: pa.Table) -> pa.Table:
        weights = table["weight"].to_numpy()
        total = float(weights.sum())
        acc = sum(np.frombuffer(x.as_py(), np.float32).astype(np.float64) * (w / total) for w, x in zip(weights, table["params"], strict=True))
        return pa.table({"place": [table["place"][0].as_py()], "weight": [total], "params": pa.array([acc.astype(np.float32).tobytes()], pa.binary())})

    while True:
        places = -(-places // FAN_IN)
        up = trained.withColumn("place", F.floor(F.col("place") / FAN_IN).cast("long"))
        trained = up.groupBy("place").applyInArrow(mean, "place long, weight double, params binary")
        if places <= 1:
            return trained


# ---------------------------------------------------------------- words and the base


def _digests(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """63-bit digests of the words of all texts, and where each text's words begin and the last ones end."""
    h, begin = word_digests([(t or "").encode("utf-8", "surrogatepass") for t in texts])
    return (h >> np.uint64(1)).astype(np.int64), np.append(begin, len(h))


def word_counts(texts: DataFrame) -> DataFrame:
    """(word, c): 63-bit word digests and their counts over all texts; the end of a text is digest -1."""
    def run(batches):
        keep_memory()
        parts, held, ends = [], 0, 0

        def out():
            unique, place = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
            return pa.RecordBatch.from_arrays(
                [pa.array(unique), pa.array(np.bincount(place, weights=np.concatenate([p[1] for p in parts])).astype(np.int64))],
                names=["word", "c"])

        for batch in batches:
            ends += batch.num_rows
            for part in laid(batch, 0, LAID_CHARS):
                parts.append(np.unique(_digests(part.column(0).to_pylist())[0], return_counts=True))
                held += len(parts[-1][0])
                if held > 1_000_000:
                    yield out()
                    parts, held = [], 0
        if held:
            yield out()
        if ends:
            yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int64()), pa.array([ends], pa.int64())], names=["word", "c"])

    return texts.select("text").mapInArrow(run, "word long, c long").groupBy("word").agg(F.sum("c").alias("c"))


def score_texts(docs: DataFrame, held_out, rank_file: str, id_column: str = "doc_id", text_column: str = "text",
                frequent_words: int = FREQUENT_WORDS) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score), one row for each input row.

    Learns from the rows where the column `held_out` is false. Null texts count as empty: one
    token, the end. Without training rows the counts are zero and the model is untrained. Null ids
    and repeated rows pass through; an empty table gives no rows; only the id and text columns
    (and what `held_out` reads) are used.
    """
    spark = docs.sparkSession
    named = docs.select(F.col(id_column).cast("long").alias("doc_id"), held_out.alias("held_out"),
                        F.col(text_column).cast("string").alias("text"))
    training = named.where("not held_out")
    counts = cut(word_counts(training), "lm-counts")
    ends = counts.where("word = -1").first()
    vocabulary = fit_vocabulary(training, rank_file, int(ends["c"]) if ends else 0)
    coded = encode_texts(named.withColumn("key", F.xxhash64("doc_id", "text")), rank_file, vocabulary)
    params = spark.sparkContext.broadcast(_pack(train_model(coded.where("not held_out").select("key", "ids"))))
    all_of = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
    total, vocabulary = int(all_of["n"]), int(all_of["v"])
    # the most frequent words, by steps of an eighth of an octave: as many whole steps as fit
    step = F.floor(F.log2("c") * 8)
    from_step, held = 10_000, 0
    for r in sorted(counts.groupBy(step.alias("s")).agg(F.count("*").alias("k")).collect(), key=lambda r: -r["s"]):
        if held + r["k"] > frequent_words:
            break
        from_step, held = r["s"], held + r["k"]
    top = counts.where(step >= from_step).toArrow().sort_by("word")
    frequent = spark.sparkContext.broadcast((top["word"].to_numpy(), top["c"].to_numpy()))
    denominator = total + 0.5 * (vocabulary + 1)

    def run(batches):
        keep_memory()
        scorer = Scorer(_unpack(params.value))
        keys, counts_of = frequent.value
        logs = np.log10((counts_of + 0.5) / denominator)
        place = np.searchsorted(keys, -1)
        end = float(logs[place]) if place < len(keys) and keys[place] == -1 else None
        for batch in batches:
            for part in laid(batch, 2, LAID_CHARS):
                texts = part.column(2).to_pylist()
                score = text_logp(scorer, _ids(part.column(3))) / math.log(10)
                word, cuts = _digests(texts)
                at = np.searchsorted(keys, word)
                at[at == len(keys)] = 0
                found = keys[at] == word if len(keys) else np.zeros(len(word), bool)
                n, sums = np.concatenate([[0], np.cumsum(found)]), np.concatenate([[0.0], np.cumsum(np.where(found, logs[at], 0.0) if len(keys) else 0.0 * word)])
                known, base = n[cuts[1:]] - n[cuts[:-1]], sums[cuts[1:]] - sums[cuts[:-1]]
                rare = [word[lo:hi][~found[lo:hi]] for lo, hi in zip(cuts[:-1], cuts[1:], strict=True)]
                if end is None:
                    rare = [np.append(r, -1) for r in rare]
                else:
                    known, base = known + 1, base + end
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(np.diff(cuts) + 1, pa.int64()), pa.array(known, pa.int64()),
                     pa.array(base, pa.float64()), pa.array(score, pa.float64()), pa.array(rare, pa.list_(pa.int64()))],
                    names=["doc_id", "held_out", "n_tokens", "known", "base", "score", "rare"])

    scored = cut(coded.select("doc_id", "held_out", "text", "ids").mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, known long, base double, score double, "
                                       "rare array<long>").withColumn("row", F.monotonically_increasing_id()), "lm-scored")
    rare = scored.select("row", F.explode("rare").alias("word")).groupBy("row", "word").agg(F.count("*").alias("k"))
    seldom = counts.where(step < from_step)
    c = F.coalesce(F.col("c"), F.lit(0))
    parts = rare.join(seldom, "word", "left").groupBy("row").agg(
        F.sum(F.when(c > 0, F.col("k")).otherwise(0)).alias("known2"),
        F.sum(F.col("k") * F.log10((c + 0.5) / F.lit(float(denominator)))).alias("base2"))
    return scored.drop("rare").join(parts, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + F.coalesce("known2", F.lit(0))).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"), (F.col("base") + F.coalesce("base2", F.lit(0.0))).alias("base_score"), "score")
