"""What the operators of this subpackage share: table reading, written cuts, crc folds."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words as the contracts define them: everything between ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder the cluster names in spark.checkpoint.dir (or that the caller set on the context).

    Without one this raises: a folder of the driver's machine is out of the executors' reach.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="patternjoin-")  # a single process: any folder is shared
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def stretches(sizes: Sequence[int], most: int) -> Iterator[tuple[int, int]]:
    """Consecutive ranges of about `most` in sum; what is larger alone stands alone."""
    lo, held = 0, 0
    for i, n in enumerate(sizes):
        if held and held + n > most:
            yield lo, i
            lo, held = i, 0
        held += n
    if lo < len(sizes):
        yield lo, len(sizes)


def laid(batch: pa.RecordBatch, column: int, most: int) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about `most` characters of text in one column."""
    sizes = [len(t.as_py() or "") for t in batch.column(column)]
    for lo, hi in stretches(sizes, most):
        yield batch.slice(lo, hi - lo)


def cut(df: DataFrame, label: str = "cut", partition_by: str | None = None) -> DataFrame:
    """Write df once to the shared folder and read it back: lineage ends here and
    any executor can be lost afterwards without recomputing what came before."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def forget(df: DataFrame | None) -> None:
    """Delete the files behind a cut() that nothing reads any more."""
    path = getattr(df, "_cut_path", None)
    if path is None:
        return
    spark = df.sparkSession
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def crc_fold(id_column: str, modulus: int) -> Column:
    """crc32 of the id written as decimal text, modulo `modulus`; null ids count as fold -1."""
    return F.coalesce(F.crc32(F.col(id_column).cast("string").cast("binary")) % modulus, F.lit(-1))
