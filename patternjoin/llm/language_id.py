"""Language identification with bit-sliced Bloom filters over byte n-grams.

Slot s of the filter holds a mask with one bit for each language, so h lookups and an AND give
every language that contains an n-gram. The hits of a language over a text, less what false
positives alone would give, decide.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import laid

GRAM = 4
SLOT_BITS = 20
#: Documents per language that the filter is fitted on, chosen by a hash of their id.
SAMPLE_DOCS = 4_000
#: N-grams per language in the filter, the most frequent ones.
GRAMS_PER_LANGUAGE = 60_000
#: An n-gram belongs to every language where it is at least this fraction as frequent as where it is most frequent.
RELATIVE_RATE = 0.25
MAX_LANGUAGES = 64
#: Characters of text that are laid out at once; a longer text is taken alone.
LAID_CHARS = 500_000

_letter = regex.compile(r"\p{L}").search
_FACTORS = (np.uint32(0x9E3779B1), np.uint32(0x85EBCA77))


def _laid_out(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """N-gram codes of all texts in one array, with each text's first and last place."""
    raw = [f" {t.lower()} ".encode("utf-8", "surrogatepass") if t else b"" for t in texts]
    sizes = np.fromiter(map(len, raw), np.int64, len(raw))
    ends = np.cumsum(sizes)
    starts = ends - sizes
    b = np.frombuffer(b"".join(raw) + bytes(GRAM), np.uint8).astype(np.uint32)
    n = len(b) - GRAM
    codes = b[:n].copy()
    for i in range(1, GRAM):
        codes |= b[i:n + i] << np.uint32(8 * i)
    return codes, starts, np.maximum(starts, ends - GRAM + 1)


def _slots(codes: np.ndarray) -> list[np.ndarray]:
    out = []
    for f in _FACTORS:
        h = codes * f
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x2C1B3C6D)
        out.append(h >> np.uint32(32 - SLOT_BITS))
    return out


class LanguageFilter:
    def __init__(self, languages: list[str], grams: dict[str, np.ndarray], prior: str | None):
        """grams: the n-gram codes that each language contains."""
        if len(languages) > MAX_LANGUAGES:
            raise ValueError(f"{len(languages)} languages; a slot's mask has {MAX_LANGUAGES} bits")
        self.languages = languages
        self.prior = prior
        width = next(w for w in (8, 16, 32, 64) if len(languages) <= w)
        self.masks = np.zeros(1 << SLOT_BITS, f"uint{width}")
        for bit, language in enumerate(languages):
            for s in _slots(grams[language]):
                self.masks[s] |= self.masks.dtype.type(1 << bit)
        filled = [np.mean((self.masks >> self.masks.dtype.type(i)) & self.masks.dtype.type(1)) for i in range(len(languages))]
        self.false_rate = np.array(filled, float) ** len(_FACTORS)

    def decide(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        codes, starts, ends = _laid_out(texts)
        first, second = _slots(codes)
        hit = self.masks[first] & self.masks[second]
        n = (ends - starts).astype(float)
        counts = np.zeros((len(texts), len(self.languages)))
        one = hit.dtype.type(1)
        for i in range(len(self.languages)):
            total = np.concatenate([[0], np.cumsum((hit >> hit.dtype.type(i)) & one, dtype=np.int64)])
            raw = total[ends] - total[starts]
            counts[:, i] = np.maximum(0.0, (raw - n * self.false_rate[i]) / (1 - self.false_rate[i]))
        languages, scores = [], []
        for text, row in zip(texts, counts, strict=True):
            if not text or not _letter(text):
                languages.append("und")
                scores.append(0.0)
                continue
            total = row.sum()
            if total <= 0:
                languages.append(self.prior)
                scores.append(0.0)
            else:
                best = int(row.argmax())
                languages.append(self.languages[best])
                scores.append(float(min(1.0, row[best] / total)))
        return languages, scores


def fit_filter(labelled: DataFrame, sample_docs: int = SAMPLE_DOCS) -> LanguageFilter:
    """Fit on (doc_id, text, lang) rows; rows without a language are left out.

    What reaches the driver is bounded by languages times GRAMS_PER_LANGUAGE.
    """
    rows = labelled.where("lang is not null and text is not null")
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).limit(MAX_LANGUAGES + 1).collect()}
    languages = sorted(sizes)
    if not languages:
        return LanguageFilter([], {}, None)
    share = F.create_map(*[F.lit(x) for l in languages for x in (l, min(1.0, sample_docs / sizes[l]))])
    place = (F.xxhash64("doc_id") % F.lit(1_000_000) + F.lit(1_000_000)) % F.lit(1_000_000)
    sample = rows.where(place < F.element_at(share, F.col("lang")) * 1_000_000)

    def grams(batches):
        held: dict[str, list] = {}

        def out():
            for language, parts in held.items():
                codes = np.concatenate([p[0] for p in parts])
                n = np.concatenate([p[1] for p in parts])
                unique, place = np.unique(codes, return_inverse=True)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([language] * len(unique)), pa.array(unique.astype(np.int64)),
                     pa.array(np.bincount(place, weights=n).astype(np.int64))], names=["lang", "gram", "n"])
            held.clear()

        kept = 0
        for batch in batches:
            for part in laid(batch, 0, LAID_CHARS):
                langs = part.column(1).to_pylist()
                codes, starts, ends = _laid_out(part.column(0).to_pylist())
                for language in set(langs):
                    own = [codes[s:e] for s, e, l in zip(starts, ends, langs, strict=True) if l == language]
                    unique, n = np.unique(np.concatenate(own), return_counts=True)
                    held.setdefault(language, []).append((unique, n))
                    kept += len(unique)
                if kept > 1_000_000:
                    yield from out()
                    kept = 0
        yield from out()

    counted = sample.select("text", "lang").mapInArrow(grams, "lang string, gram long, n long").groupBy("lang", "gram").agg(
        F.sum("n").alias("n"))
    from pyspark.sql import Window

    # the rank is taken over the n-grams of a sample, whose size is bounded above
    top = counted.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))).where(
        F.col("r") <= 2 * GRAMS_PER_LANGUAGE).select("lang", "gram", "n").toPandas()
    totals = top.groupby("lang")["n"].sum()
    top["rate"] = top["n"] / top["lang"].map(totals)
    top["best"] = top.groupby("gram")["rate"].transform("max")
    top = top[top["rate"] >= RELATIVE_RATE * top["best"]]
    found = {}
    for language in languages:
        own = top[top["lang"] == language].sort_values(["rate", "gram"], ascending=[False, True])
        found[language] = own["gram"].to_numpy(np.int64)[:GRAMS_PER_LANGUAGE].astype(np.uint32)
    return LanguageFilter(languages, found, max(languages, key=lambda l: sizes[l]))


def identify(docs: DataFrame, model: LanguageFilter, text_column: str = "text", language_column: str = "lang_pred",
             score_column: str = "score", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """`keep` columns plus prediction and score, one row for each input row.

    Null texts and texts without a letter are `und` with score 0; a text with letters but no known
    n-gram gets the most frequent language with score 0, and a null one where the model has learnt
    none. Ties go to the language that sorts first.
    Very long texts are taken whole; an empty table gives no rows.
    """
    blob = docs.sparkSession.sparkContext.broadcast(model)  # one mask per slot: 1 to 8 MB, whatever the data

    def run(batches):
        for batch in batches:
            languages, scores = [], []
            for part in laid(batch, batch.num_columns - 1, LAID_CHARS):
                a, b = blob.value.decide(part.column(part.num_columns - 1).to_pylist())
                languages += a
                scores += b
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], pa.array(languages, pa.string()), pa.array(scores, pa.float64())],
                names=[*batch.schema.names[:-1], language_column, score_column])

    kept = docs.select(*keep)
    text = "text"
    while text.lower() in {c.lower() for c in kept.columns}:  # its own name, whatever else is kept
        text += "_"
    schema = kept.schema.add(language_column, "string").add(score_column, "double")
    return docs.select(*keep, F.col(text_column).cast("string").alias(text)).mapInArrow(run, schema)
