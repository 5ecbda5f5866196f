"""MinHash near-duplicates from bottom-k sketches of one hash function.

1. every text becomes its set of word shingles (64-bit hashes) and the k smallest of them;
2. texts with equal sets collapse to one class;
3. inverted lists of the retained values generate overlaps: a pair of sets that is similar
   enough shares at least `t` retained values, so only the s - t + 1 rarest values of each
   sketch have to be listed (a common passage never drives the lists);
4. within a list, members are compared with the list's hub, so a large group of copies costs a
   star and not all its pairs; members that the star leaves outside the group's largest
   component are then compared with the whole group, block by block, and only links come out;
5. the sketch of the union estimates each candidate; exact Jaccard on the full sets decides.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, forget, laid, stretches
from .components import connected_components
from .suffix_dedup import key_filter
from .words import MIX, MULT, word_digests

K = 64
#: Overlap that a pair of sketches of K values must show. For similarity 0.8 the overlap is
#: binomial(64, 0.8) or more; below 34 it falls with a probability of about 3e-7.
MIN_OVERLAP = 34

#: Characters of text whose shingles are laid out at once; a longer text is taken alone.
LAID_CHARS = 500_000

def _chained(h: np.ndarray, span: int) -> np.ndarray:
    """Digest of the `span` words from each place."""
    acc = np.full(len(h) - span + 1, span, np.uint64)
    for i in range(span):
        acc = (acc ^ h[i:len(h) - span + 1 + i]) * MIX
        acc ^= acc >> np.uint64(29)
    acc *= MULT
    acc ^= acc >> np.uint64(32)
    return acc >> np.uint64(1)


def shingle_sets(texts: list[str | None], width: int) -> list[np.ndarray]:
    """Sorted distinct 63-bit shingle digests of each text; empty for null or wordless texts."""
    out: list[np.ndarray] = []
    for lo, hi in stretches([len(t or "") for t in texts], LAID_CHARS):
        h, begin = word_digests([(t or "").encode("utf-8", "surrogatepass") for t in texts[lo:hi]])
        all_ = _chained(h, width) if len(h) >= width else None
        for s, e in zip(begin.tolist(), [*begin[1:].tolist(), len(h)], strict=True):
            out.append(np.unique(all_[s:e - width + 1] if e - s >= width else _chained(h[s:e], e - s)) if e > s else h[:0])
    return out


def shingle_set(text: str | None, width: int) -> np.ndarray:
    return shingle_sets([text], width)[0]


def _sketches(width: int, k: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("fp", pa.binary()),
                        ("sk", pa.list_(pa.int64()))])

    def run(batches):
        for batch in batches:
            for part in laid(batch, 1, LAID_CHARS):
                ns, fps, sks = [], [], []
                for s in shingle_sets(part.column(1).to_pylist(), width):
                    ns.append(len(s))
                    fps.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                    sks.append(s[:k].astype(np.int64))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(ns, pa.int64()), pa.array(fps, pa.binary()),
                     pa.array(sks, pa.list_(pa.int64()))], schema=schema)

    return run


def _verify(width: int, num: int, den: int):
    def run(batches):
        for batch in batches:
            for part in laid(batch, 3, LAID_CHARS):
                ids = part.column(0).to_pylist()
                turn = [i for i, x in enumerate(ids) if not i or x != ids[i - 1]]
                own = shingle_sets(part.column(2).take(pa.array(turn, pa.int64())).to_pylist(), width)
                keep, at = [], -1
                for i, other in enumerate(shingle_sets(part.column(3).to_pylist(), width)):
                    if at + 1 < len(turn) and turn[at + 1] == i:
                        at += 1
                    common = len(np.intersect1d(own[at], other, assume_unique=True))
                    if den * common >= num * (len(own[at]) + len(other) - common):
                        keep.append(i)
                yield part.select([0, 1]).take(pa.array(keep, pa.int64())).rename_columns(["a", "b"])

    return run


def _texts_of(texts: DataFrame, wanted: DataFrame) -> DataFrame:
    """Texts of the wanted rids; a bounded filter keeps most others out of the shuffle."""
    wanted = cut(wanted, "near-wanted")
    known = texts.sparkSession.sparkContext.broadcast(key_filter(wanted, "rid", wanted.count()))

    def may_be_wanted(batches):
        for batch in batches:
            yield batch.filter(pa.array(known.value.holds(batch.column(0).to_numpy())))

    near = texts.where("rid is not null").select("rid", "text").mapInArrow(may_be_wanted, "rid long, text string")
    # repeated rows of an id and a text are one text
    found = near.join(wanted, "rid", "left_semi").groupBy("rid", F.xxhash64("text").alias("t")).agg(F.first("text").alias("text"))
    found = cut(found.drop("t"), "near-texts")
    forget(wanted)
    return found


def _linked(pairs: DataFrame, reps: DataFrame, texts: DataFrame, width: int, num: int, den: int,
            k: int, min_overlap: int) -> DataFrame:
    """The pairs (a < b) whose union sketch allows and whose full sets confirm the similarity."""
    left = reps.select(F.col("rid").alias("a"), F.col("n").alias("na"), F.col("sk").alias("ska"))
    right = reps.select(F.col("rid").alias("b"), F.col("n").alias("nb"), F.col("sk").alias("skb"))
    union = F.slice(F.array_sort(F.array_union("ska", "skb")), 1, k)
    shared = F.size(F.array_intersect(union, F.array_intersect("ska", "skb")))
    likely = (pairs.join(left, "a").join(right, "b")
              .where(den * F.least("na", "nb") >= num * F.greatest("na", "nb"))
              .where(F.when((F.col("na") <= k) & (F.col("nb") <= k) & (F.size(F.array_union("ska", "skb")) <= k),
                            den * shared >= num * F.size(F.array_union("ska", "skb")))
                     .otherwise(shared >= min_overlap))
              .select("a", "b"))
    likely = cut(likely, "near-likely")
    needed = likely.select(F.col("a").alias("rid")).union(likely.select("b")).distinct()
    sets = _texts_of(texts, needed)
    full = (likely.join(sets.select(F.col("rid").alias("b"), F.col("text").alias("tb")), "b")
            .join(sets.select(F.col("rid").alias("a"), F.col("text").alias("ta")), "a")
            .select("a", "b", "ta", "tb"))
    links = cut(full.mapInArrow(_verify(width, num, den), "a long, b long"), "near-links")
    forget(likely)
    forget(sets)
    return links


def _components_of(reps: DataFrame, edges: DataFrame) -> DataFrame:
    labels = connected_components(edges)
    return reps.select("rid").join(labels, F.col("rid") == F.col("node"), "left").select(
        "rid", F.coalesce("root", "rid").alias("comp"))


def _block_pairs(num: int, den: int, k: int, min_overlap: int, plausible: bool):
    """Queries against candidates of one pair of blocks, by the overlaps of their value arrays.

    On sketches (plausible) it names the members that have a possible partner, on full sets the links.
    """
    def run(block: pa.Table) -> pa.Table:
        ids = block["rid"].to_numpy()
        comp = block["comp"].to_numpy()
        n = block["n"].to_numpy()
        asks = block["asks"].to_numpy(zero_copy_only=False)
        sets = [np.frombuffer(x.as_py(), np.uint64) for x in block["members"]]
        cand = np.nonzero(~asks)[0]
        a, b = [], []
        if len(cand) and asks.any():
            sizes = np.array([len(sets[i]) for i in cand])
            universe, place = np.unique(np.concatenate([sets[i] for i in cand]), return_inverse=True)
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            mark = np.zeros(len(universe), np.int32)
            for q in np.nonzero(asks)[0]:
                at = np.searchsorted(universe, sets[q])
                at[at == len(universe)] = 0
                at = at[universe[at] == sets[q]]
                mark[at] = 1
                common = np.add.reduceat(mark[place], starts)
                mark[at] = 0
                fits = den * common >= num * (n[q] + n[cand] - common)
                if plausible:  # whole sets of k values at most decide at once, larger ones by their overlap
                    fits = np.where((n[q] <= k) & (n[cand] <= k), fits, common >= min_overlap)
                    fits &= den * np.minimum(n[q], n[cand]) >= num * np.maximum(n[q], n[cand])
                other = ids[cand[fits & (comp[cand] != comp[q])]]
                a.append(np.minimum(other, ids[q]))
                b.append(np.maximum(other, ids[q]))
        left = np.concatenate(a) if a else np.empty(0, np.int64)
        right = np.concatenate(b) if b else left
        if plausible:
            found = np.unique(np.concatenate([left, right]))
            return pa.table({"p": np.full(len(found), block["p"][0].as_py(), np.int64), "rid": found.astype(np.int64)})
        return pa.table({"a": left.astype(np.int64), "b": right.astype(np.int64)})

    return run


#: Values that one block of a group holds: two blocks are what a task has in memory.
BLOCK_VALUES = 500_000


def _in_blocks(members: DataFrame, weight, run, schema: str) -> DataFrame:
    """Deal (p, rid, comp, n, members) over pairs of blocks: outside the largest component against all."""
    parts = members.groupBy("p", "comp").agg(F.sum(weight).alias("w"))
    shape = parts.groupBy("p").agg(F.max_by("comp", F.struct("w", "comp")).alias("main"), F.sum("w").alias("all_w"),
                                   F.max("w").alias("main_w")).where("all_w > main_w").select(
        "p", "main", F.ceil(F.col("all_w") / BLOCK_VALUES).cast("int").alias("cand_blocks"),
        F.ceil((F.col("all_w") - F.col("main_w")) / BLOCK_VALUES).cast("int").alias("query_blocks"))
    rows = members.join(shape, "p")
    slot = F.xxhash64("rid").bitwiseAND(F.lit(2**62 - 1))
    span = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    kept = ["p", "rid", "comp", "n", "members"]
    cands = rows.select(*kept, F.lit(False).alias("asks"), (slot % F.col("cand_blocks")).cast("int").alias("cb"),
                        F.explode(span("query_blocks")).alias("qb"))
    asking = rows.where("comp <> main").select(*kept, F.lit(True).alias("asks"), F.explode(span("cand_blocks")).alias("cb"),
                                               (slot % F.col("query_blocks")).cast("int").alias("qb"))
    # dealt by pair of blocks: without this the groups would stay where the join on p has put them, a hot one in one task
    dealt = cands.unionByName(asking).repartition("p", "cb", "qb")
    return dealt.groupBy("p", "cb", "qb").applyInArrow(run, schema).distinct()


def _across(groups: DataFrame, comp: DataFrame, reps: DataFrame, texts: DataFrame, width: int, num: int, den: int,
            k: int, min_overlap: int) -> DataFrame:
    """Links (a < b) inside the groups between classes that are not joined yet.

    The members outside a group's largest component are its queries; they are compared with all
    members, block by block: first by sketch, which leaves out members without a possible partner,
    then on full sets. Only links leave a task.
    """
    placed = groups.join(comp, "rid")
    open_groups = placed.where("p <> rid").groupBy("p").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where(
        "lo <> hi").select("p")

    def packed(batches):
        for batch in batches:
            raw = [np.array(x.as_py(), np.uint64).tobytes() for x in batch.column(4)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(raw, pa.binary())], names=["p", "rid", "comp", "n", "members"])

    layout = "p long, rid long, comp long, n long, members binary"
    sketched = cut(placed.join(open_groups, "p").join(reps.select("rid", "n", "sk"), "rid").select("p", "rid", "comp", "n", "sk").mapInArrow(
        packed, layout), "near-open")
    hopeful = cut(_in_blocks(sketched, F.least("n", F.lit(k)), _block_pairs(num, den, k, min_overlap, True), "p long, rid long"), "near-hopeful")

    def set_of(batches):
        for batch in batches:
            for part in laid(batch, 1, LAID_CHARS):
                raw = [s.tobytes() for s in shingle_sets(part.column(1).to_pylist(), width)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(raw, pa.binary())], names=["rid", "members"])

    found = _texts_of(texts, hopeful.select("rid").distinct())
    sets = found.select("rid", "text").mapInArrow(set_of, "rid long, members binary")
    full = sketched.drop("members").join(hopeful, ["p", "rid"], "left_semi").join(sets, "rid")
    links = cut(_in_blocks(full, F.col("n"), _block_pairs(num, den, k, min_overlap, False), "a long, b long"), "near-links")
    for done in (sketched, hopeful, found):
        forget(done)
    return links


def near_duplicates(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", width: int = 5,
                    num: int = 80, den: int = 100, k: int = K, min_overlap: int = MIN_OVERLAP) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept), one row for each input row.

    Null, empty and wordless texts have the empty set and link with nothing. Rows with a null id
    take no part: component_id is null and kept is true. Repeated rows share their id's component.
    Only the two named columns are read, so further columns cannot clash. An empty table gives no rows.
    """
    named = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).cast("string").alias("text"))
    sig = cut(named.mapInArrow(_sketches(width, k), "doc_id long, n_shingles long, fp binary, sk array<long>"),
              "near-sig")
    reps = cut(sig.where("n_shingles > 0 and doc_id is not null").groupBy("fp").agg(
        F.min("doc_id").alias("rid"), F.first("n_shingles").alias("n"), F.first("sk").alias("sk")), "near-reps")
    # the sketches are those of the classes from here on
    sketched, sig = sig, cut(sig.select("doc_id", "n_shingles", "fp"), "near-names")
    forget(sketched)
    # a doc_id that is repeated with different texts stands for all their sets: any of them may link it
    texts = named.select(F.col("doc_id").alias("rid"), "text")

    values = reps.select("rid", "n", F.explode("sk").alias("v"))
    common = values.groupBy("v").agg(F.count("*").alias("df")).where("df > 1")
    size = F.least("n", F.lit(k))
    # sets this small keep all their values in the partner's sketch as well, so the exact bound holds
    overlap = F.when(F.col("n") <= (k * num) // den, F.ceil(F.col("n") * num / den)).otherwise(F.lit(min_overlap))
    listed = (values.join(common, "v").groupBy("rid", "n").agg(F.sort_array(F.collect_list(F.struct("df", "v"))).alias("vs"))
              .withColumn("room", (size - overlap + 1 - (size - F.size("vs"))).cast("int"))
              .where("room > 0")
              # the text that others were copied from holds the values most of them share
              .select("rid", "n", F.aggregate("vs", F.lit(0).cast("long"), lambda acc, x: acc + x["df"]).alias("hub"),
                      F.explode(F.slice("vs", F.lit(1), F.col("room"))).alias("x"))
              .select("rid", "n", "hub", F.col("x.v").alias("v")))
    index = cut(listed, "near-index")

    # a list's pivot is its hub; lists of one group of copies have the same hub, so they fall together
    hubs = index.groupBy("v").agg(F.max_by(F.struct("rid", "n"), F.struct("hub", -F.col("rid"))).alias("top"),
                                  F.count("*").alias("c")).where("c > 1").select(
        "v", F.col("top.rid").alias("p"), F.col("top.n").alias("pn"), "c")
    # a list of two is settled by its one pair; only longer ones can join members beside their hub
    groups = cut(index.join(hubs, "v").groupBy("p", "pn", "rid", "n").agg(F.max("c").alias("c")), "near-groups")
    forget(index)
    alike = den * F.least("n", "pn") >= num * F.greatest("n", "pn")
    pairs = groups.where("p <> rid").where(alike).select(F.least("rid", "p").alias("a"), F.greatest("rid", "p").alias("b")).distinct()
    groups = groups.where("c > 2").select("p", "rid")
    edges = _linked(pairs, reps, texts, width, num, den, k, min_overlap)
    comp = _components_of(reps, edges)
    edges = cut(edges.unionByName(_across(groups, comp, reps, texts, width, num, den, k, min_overlap)), "near-links")
    comp = _components_of(reps, edges)
    named_class = reps.select("fp", "rid").join(comp, "rid").select("fp", "comp")
    out = sig.select("doc_id", "n_shingles", "fp").join(named_class, "fp", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"),
                      F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))
