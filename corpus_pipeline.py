"""Five stages from raw documents to token ids.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns a
DataFrame; all but the last return the columns of documents, further columns included.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternjoin.llm.byte_bpe import byte_bpe
from patternjoin.llm.common import cut, table
from patternjoin.llm.language_id import fit_filter, identify
from patternjoin.llm.near_dedup import near_duplicates
from patternjoin.llm.source_mixing import mix_sources
from patternjoin.llm.suffix_dedup import remove_repeats

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def _free(docs: DataFrame, name: str) -> str:
    """A column name that docs does not have."""
    while name.lower() in {c.lower() for c in docs.columns}:
        name += "_"
    return name


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language go; a missing label is filled in.

    Null, empty and letterless texts have none; very long texts are judged whole. Null ids and sources
    and repeated rows pass through; where no row has a label, all texts with letters stay without one. An empty
    table gives no rows; further columns come back as they are, whatever their names.
    """
    found, score = _free(docs, "found"), _free(docs, "found_score")
    model = fit_filter(docs.select("doc_id", "text", "lang"))
    named = identify(docs, model, language_column=found, score_column=score, keep=tuple(docs.columns))
    label = F.coalesce("lang", found).alias("lang")
    return named.where(F.coalesce(F.col(found) != "und", F.lit(True))).select(*[label if c == "lang" else c for c in docs.columns])


def one_of_each(docs: DataFrame) -> DataFrame:
    """Of rows that share 0.8 of their five-word shingles, the one with the smallest id stays, rows without one last.

    Every row takes part under a number of its own, so repeated rows are copies as well, and texts
    that differ under one id are not.
    """
    row, root = _free(docs, "row"), _free(docs, "component_id")
    rows = cut(docs.withColumn(row, F.monotonically_increasing_id()), "near-rows")
    classes = near_duplicates(rows, id_column=row).select(F.col("doc_id").alias(row), F.col("component_id").alias(root))
    first = rows.select(row, "doc_id").join(classes, row).groupBy(root).agg(
        F.min(F.struct(F.col("doc_id").isNull(), "doc_id", row)).alias("first")).select(f"first.{row}")
    return rows.join(first, row, "left_semi").select(*docs.columns)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class of near copies; rows without an id stay until the next stage settles them.

    Ties go to the smallest id, of repeated rows one stays. Null, empty and wordless texts are copies of
    nothing; very long texts are compared whole. An empty table gives no rows; further columns come back.
    """
    return one_of_each(docs.where("doc_id is not null")).unionByName(docs.where("doc_id is null"))


def suffix_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Byte strings of 200 that occur elsewhere as well are cut out of the texts.

    Copies would lose all of their text to each other, so rows without an id are settled first. Null
    texts become empty, texts of fewer than 200 bytes stay as they are, very long ones are cut like
    others; n_chars follows where something was cut or it was null. An empty table gives no rows;
    further columns come back as they are, whatever their names.
    """
    if not docs.where("doc_id is null").isEmpty():
        docs = one_of_each(docs)
    cleaned = remove_repeats(docs.select(*docs.columns), keep_text=True, carry=tuple(c for c in docs.columns if c != "text"))
    text = F.when(F.col("n_removed") > 0, F.length("kept_text"))
    columns = [F.col("kept_text").alias("text") if c == "text" else
               F.coalesce(text.cast("long"), F.col("carried.n_chars")).alias("n_chars") if c == "n_chars" else
               F.col("carried").getField(c).alias(c) for c in docs.columns]
    return cleaned.select(*columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document stands as often as the mix uses it; those it does not use go.

    Null, empty and wordless texts have size 0 and are never used. Null sources form a source of their
    own. Repeated ids stand as often as the most used of their rows. An empty table gives no rows;
    further columns come back as they are, whatever their names.
    """
    key, n, turn = _free(docs, "key"), _free(docs, "uses"), _free(docs, "turn")
    uses = mix_sources(docs.select("doc_id", "text", "source")).where("uses > 0").groupBy(
        F.col("doc_id").alias(key)).agg(F.max("uses").alias(n))
    return docs.join(uses, F.col("doc_id").eqNullSafe(F.col(key))).withColumn(
        turn, F.explode(F.sequence(F.lit(1), F.col(n)))).select(*docs.columns)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, decoded_ok, token_ids) of every document.

    Null texts count as empty: no tokens. Very long texts are encoded whole. Null and repeated ids pass
    through; an empty table gives no rows; further columns are not read.
    """
    return byte_bpe(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES: list[tuple[str, Stage]] = [
    ("language_id", language_stage),
    ("near_dedup", near_dedup_stage),
    ("suffix_dedup", suffix_dedup_stage),
    ("source_mixing", mixing_stage),
    ("byte_bpe", encoding_stage),
]

#: Sketches, suffix arrays and merge replay are beyond SQL: tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
