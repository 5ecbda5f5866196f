"""Byte-level BPE by corpus-level merge replay.

The distinct pieces of a block of texts are laid out as one chain of tokens. An inverted index
maps the rank of each adjacent token pair to the positions where it stands; ranks are taken from
a heap in ascending order and one merge is applied at all its positions at once, which touches
the two neighbouring pairs only. Pieces are cached per worker, so a piece is replayed once and
not once for each occurrence.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import laid

#: Pieces and pair ranks a task keeps; beyond it new ones last for one block, so memory does not follow the corpus.
CACHED_PIECES, CACHED_PAIRS = 150_000, 300_000
#: Characters of text, and distinct pieces, that are laid out at once.
BLOCK_CHARS, BLOCK_PIECES = 1_000_000, 20_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


class MergeReplay:
    """Encoder and decoder over one rank file."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.split = regex.compile(pattern).findall
        self.token_bytes = {rank: token for token, rank in ranks.items()}
        self.digits = {rank: str(rank) for rank in self.token_bytes}
        self.pieces: dict[str, tuple[int, ...]] = {}
        self.pair_rank: dict[int, int] = {}
        # ranks of two single bytes, as a table: the first pairs of every piece are looked up at once
        self.byte_rank = np.array([ranks[bytes((b,))] for b in range(256)], np.int64)
        self.first_rank = np.array([[ranks.get(bytes((a, b)), -1) for b in range(256)] for a in range(256)], np.int64)

    def _rank(self, left: int, right: int) -> int:
        """Rank of the token that two tokens make, or -1."""
        key = left << 32 | right
        try:
            return self.pair_rank[key]
        except KeyError:
            found = self.ranks.get(self.token_bytes[left] + self.token_bytes[right], -1)
            if len(self.pair_rank) > CACHED_PAIRS:
                self.pair_rank.clear()
            self.pair_rank[key] = found
            return found

    def replay(self, pieces: list[str]) -> list[tuple[int, ...]]:
        """Token ids of every piece: all merges of the block in rank order."""
        raws = [p.encode("utf-8", "surrogatepass") for p in pieces]
        sizes = np.fromiter(map(len, raws), np.int64, len(raws))
        starts = np.cumsum(sizes + 1) - sizes - 1
        n = int((sizes + 1).sum())
        laid = np.full(n, -1, np.int64)  # the end of a piece: nothing merges across it
        data = np.frombuffer(b"".join(raws), np.uint8)
        at = np.arange(len(data)) + np.repeat(np.arange(len(raws)), sizes)
        laid[at] = self.byte_rank[data]
        pair = np.full(n, -1, np.int64)
        joined = np.nonzero(at[1:] == at[:-1] + 1)[0]
        pair[at[joined]] = self.first_rank[data[joined], data[joined + 1]]
        place = np.nonzero(pair >= 0)[0]
        place = place[np.argsort(pair[place], kind="stable")]
        ranks, first = np.unique(pair[place], return_index=True)
        index = dict(zip(ranks.tolist(), [p.tolist() for p in np.split(place, first[1:])], strict=True)) if len(place) else {}
        tokens: list[int] = laid.tolist()
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        heap = list(index)
        heapq.heapify(heap)
        rank_of, known = self._rank, self.pair_rank
        while heap:
            rank = heapq.heappop(heap)
            positions = index.pop(rank, None)
            if positions is None:
                continue
            positions.sort()
            for k, i in enumerate(positions):
                a = tokens[i]
                if a < 0:
                    continue
                j = after[i]
                b = tokens[j]
                if b < 0:
                    continue
                r = known.get(a << 32 | b)
                if (rank_of(a, b) if r is None else r) != rank:
                    continue  # a neighbour took part in an earlier merge
                tokens[i] = rank
                tokens[j] = -2
                q = after[i] = after[j]
                before[q] = i
                lower = False
                c = tokens[q]
                if c >= 0:
                    r = known.get(rank << 32 | c)
                    if r is None:
                        r = rank_of(rank, c)
                    if r >= 0:
                        if r in index:
                            index[r].append(i)
                        else:
                            index[r] = [i]
                            heapq.heappush(heap, r)
                        lower = r <= rank
                p = before[i]
                c = tokens[p] if p >= 0 else -1
                if c >= 0:
                    r = known.get(c << 32 | rank)
                    if r is None:
                        r = rank_of(c, rank)
                    if r >= 0:
                        if r in index:
                            index[r].append(p)
                        else:
                            index[r] = [p]
                            heapq.heappush(heap, r)
                        lower = lower or r <= rank
                if lower and k + 1 < len(positions):  # the new pair goes first; the rest waits
                    index.setdefault(rank, []).extend(positions[k + 1:])
                    heapq.heappush(heap, rank)
                    break
        # what is left of each piece, in order
        left = np.array(tokens, np.int64)
        kept = left[left != -2]
        cuts = np.nonzero(kept == -1)[0].tolist()
        ids = kept.tolist()
        out, lo = [], 0
        for hi in cuts:
            out.append(tuple(ids[lo:hi]))
            lo = hi + 1
        return out

    def encode_all(self, texts: list[str | None]) -> list[list[int]]:
        """Ids of each text; null counts as empty."""
        split = [self.split(t) if t else [] for t in texts]
        cache = self.pieces
        fresh = list(set(chain.from_iterable(split)).difference(cache))
        if fresh:
            for lo in range(0, len(fresh), BLOCK_PIECES):
                part = fresh[lo:lo + BLOCK_PIECES]
                cache.update(zip(part, self.replay(part), strict=True))
        get = cache.__getitem__
        out = [list(chain.from_iterable(map(get, pieces))) for pieces in split]
        if len(cache) > CACHED_PIECES:  # the early, mostly frequent pieces stay
            for piece in fresh:
                del cache[piece]
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, ids))


@lru_cache(maxsize=2)
def _encoder(path: str, pattern: str) -> MergeReplay:
    return MergeReplay(read_ranks(path), pattern)


def byte_bpe(docs: DataFrame, rank_file: str, pattern: str, id_column: str = "doc_id", text_column: str = "text",
             keep_ids: bool = True) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, decoded_ok[, token_ids]), one row for each input row.

    `rank_file` is a path every executor can open (an installed vocabulary). Null texts count as
    empty: no tokens, digests of nothing. Null ids, repeated rows and ties pass through as they
    are; only the two named columns are read; an empty table gives no rows.
    """
    def encoded(bpe: MergeReplay, block: pa.RecordBatch) -> pa.RecordBatch:
        texts = block.column(1).to_pylist()
        count, ids_sha, raw_sha, same, kept = [], [], [], [], []
        for text, ids in zip(texts, bpe.encode_all(texts), strict=True):
            raw = bpe.decode(ids)
            count.append(len(ids))
            ids_sha.append(hashlib.sha256(" ".join(map(bpe.digits.__getitem__, ids)).encode()).hexdigest())
            raw_sha.append(hashlib.sha256(raw).hexdigest())
            same.append(raw == (text or "").encode("utf-8", "surrogatepass"))
            if keep_ids:
                kept.append(np.array(ids, np.int32))
        columns = [block.column(0), pa.array(count, pa.int64()), pa.array(ids_sha, pa.string()),
                   pa.array(raw_sha, pa.string()), pa.array(same, pa.bool_())]
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "decoded_ok"]
        if keep_ids:
            columns.append(pa.array(kept, pa.list_(pa.int32())))
            names.append("token_ids")
        return pa.RecordBatch.from_arrays(columns, names=names)

    def run(batches):
        bpe = _encoder(rank_file, pattern)
        try:
            for batch in batches:
                for block in laid(batch, 1, BLOCK_CHARS):
                    yield encoded(bpe, block)
        finally:  # a worker goes on to other tasks and stages: what this one has learnt goes
            bpe.pieces.clear()
            bpe.pair_rank.clear()

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, decoded_ok boolean"
    named = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).cast("string").alias("text"))
    return named.mapInArrow(run, schema + (", token_ids array<int>" if keep_ids else ""))
