"""Content-addressed WARC archive.

Payload bytes are stored once under their SHA-256; the exact record headers are stored apart,
one row for each record, with the digest of the payload they belong to. Reading checks every
stored payload against its digest and joins it to the headers again.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shared_dir

PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
REVISIT_FROM = 1000
_EOL = "\r\n"


@dataclass(frozen=True)
class Archive:
    """Where an archive lies; both tables are Parquet in a folder all executors share."""

    path: str

    @property
    def payloads(self) -> str:
        return f"{self.path}/payloads"

    @property
    def records(self) -> str:
        return f"{self.path}/records"


def write_archive(pages: DataFrame, archive: Archive, id_column: str = "page_id", url_column: str = "url",
                  body_column: str = "html", revisit_from: int = REVISIT_FROM,
                  warc_date: str = "2024-01-01T00:00:00Z") -> None:
    """One record for each row. Null bodies are empty payloads, null urls leave the target line empty.

    Of records with equal payloads of at least `revisit_from` bytes the one with the largest id is the
    response and the others revisit it; rows that repeat that id are responses as well. A row with a
    null id is a revisit of the others' response, or a response if no id is known.
    """
    spark = pages.sparkSession
    body = F.encode(F.coalesce(F.col(body_column).cast("string"), F.lit("")), "UTF-8")
    rows = pages.select(F.col(id_column).cast("long").alias("record"), F.col(url_column).cast("string").alias("target"),
                        body.alias("payload")).withColumn("digest", F.sha2("payload", 256)).withColumn(
        "n", F.octet_length("payload"))
    # copies meet on the map side first, so a payload that fills a third of the table crosses the network once a task
    rows.groupBy("digest").agg(F.first("payload").alias("payload"), F.first("n").alias("n"),
                               F.max("record").alias("newest")).write.parquet(archive.payloads)
    stored = spark.read.parquet(archive.payloads).select(
        "digest", "newest", "n", F.sha1("payload").alias("sha1"))
    named = rows.select("record", "target", "digest").join(stored, "digest")
    revisit = (F.col("n") >= revisit_from) & ~F.col("record").eqNullSafe(F.col("newest")) & F.col("newest").isNotNull()
    urn = lambda c: F.concat(F.lit("<urn:record:"), F.coalesce(c.cast("string"), F.lit("")), F.lit(">"))
    lines = [F.lit("WARC/1.1"),
             F.concat(F.lit("WARC-Type: "), F.when(revisit, "revisit").otherwise("response")),
             F.concat(F.lit("WARC-Record-ID: "), urn(F.col("record"))),
             F.lit(f"WARC-Date: {warc_date}"),
             F.concat(F.lit("WARC-Target-URI: "), F.coalesce(F.regexp_replace("target", r"[\r\n]", ""), F.lit(""))),
             F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("sha1")),
             F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), urn(F.col("newest")))),
             F.when(revisit, F.lit(f"WARC-Profile: {PROFILE}")),
             F.concat(F.lit("Content-Length: "), F.when(revisit, F.lit("0")).otherwise(F.col("n").cast("string")))]
    header = F.encode(F.concat(F.concat_ws(_EOL, *lines), F.lit(_EOL * 2)), "UTF-8")
    named.select("record", header.alias("header"), "digest").write.parquet(archive.records)


def verified_payloads(spark: SparkSession, archive: Archive) -> DataFrame:
    """(digest, payload); a stored payload that does not match its digest stops the read."""
    stored = spark.read.parquet(archive.payloads)
    sound = F.sha2("payload", 256) == F.col("digest")
    return stored.select("digest", F.when(sound, F.col("payload")).otherwise(
        F.raise_error(F.concat(F.lit("damaged payload "), F.col("digest"))).cast("binary")).alias("payload"))


def _field(header, name: str):
    return F.regexp_extract(header, rf"\r\n{name}: ([^\r]*)\r\n", 1)


def read_headers(spark: SparkSession, archive: Archive) -> DataFrame:
    """(record, record_type, refers_to, content_length, target, header, digest), parsed from the stored bytes."""
    text = F.decode("header", "UTF-8")
    number = lambda c: F.regexp_extract(c, r"<urn:record:(-?\d+)>", 1)
    as_id = lambda c: F.when(c != "", c.cast("long"))
    return spark.read.parquet(archive.records).select(
        as_id(F.regexp_extract(text, r"\r\nWARC-Record-ID: <urn:record:(-?\d+)>", 1)).alias("record"),
        _field(text, "WARC-Type").alias("record_type"), as_id(number(_field(text, "WARC-Refers-To"))).alias("refers_to"),
        _field(text, "Content-Length").cast("long").alias("content_length"),
        _field(text, "WARC-Target-URI").alias("target"),
        F.regexp_extract(text, r"\r\nWARC-Payload-Digest: sha1:([0-9a-f]{40})\r\n", 1).alias("sha1"), "header", "digest")


def reconstruct(spark: SparkSession, archive: Archive) -> DataFrame:
    """(record, warc, payload): the bytes of every original record, and the payload it stands for."""
    joined = read_headers(spark, archive).join(verified_payloads(spark, archive), "digest")
    block = F.when(F.col("record_type") == "revisit", F.lit(b"")).otherwise(F.col("payload"))
    return joined.select("record", F.concat("header", block, F.lit((_EOL * 2).encode())).alias("warc"), "payload")


def new_archive(spark: SparkSession) -> Archive:
    return Archive(f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}")


def archive_report(spark: SparkSession, archive: Archive) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) from what was stored."""
    # sizes and digests are taken from the checked bytes once for each payload, not once for each record
    measured = verified_payloads(spark, archive).select(
        "digest", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha1("payload").alias("payload_digest"))
    agrees = F.col("sha1") == F.col("payload_digest")
    return read_headers(spark, archive).join(measured, "digest").select(
        F.col("record").alias("page_id"), "payload_bytes",
        F.when(agrees, F.col("payload_digest")).otherwise(F.raise_error(F.lit("header and payload disagree"))).alias(
            "payload_digest"), "record_type", "refers_to")
