"""What the corpus operators share: reading tables, word rules, scratch tables."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed rule of every contract: a word is a run of bytes other than these.
WORD = r"[^\x20\x09-\x0D]+"
#: Bytes of text that one numpy step works on at most, unless one text is longer.
SLICE_BYTES = 1 << 20

ASCII_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents")


def remainder(modulus: int, key: str = "doc_id") -> Column:
    """The split number of a row; a null id counts as the empty string."""
    return F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")) % modulus


def scratch(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir, which all executors share.

    Only where that setting is unset (tests on one machine) a local folder is made.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = "file://" + tempfile.gettempdir() + "/vpatterns-scratch"
    return f"{base.rstrip('/')}/vp-{uuid.uuid4().hex}"


def written(df: DataFrame, folder: str, name: str) -> DataFrame:
    """The rows written as a shared Parquet table and read again, so lineage ends here."""
    path = f"{folder}/{name}"
    df.write.mode("overwrite").option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession, folder: str, name: str) -> None:
    """Remove a scratch table that nothing reads any more."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/{name}")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def tidy(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of what is written: it does so when its handles are collected."""
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.3)


def input_bytes(df: DataFrame) -> int:
    """Size of the files a frame reads, as the planner knows it; at least 1."""
    try:
        return max(1, int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().toString()))
    except Exception:  # a session without a JVM handle has no plan statistics
        return 1 << 30


def shards(df: DataFrame, bytes_each: int = 2 << 20, least: int = 64) -> int:
    """Number of hash shards that keeps one shard's share of the input near bytes_each, however large it is."""
    return int(max(least, input_bytes(df) // bytes_each))


def slices(texts, limit: int = SLICE_BYTES):
    """(start, stop) runs of a list of byte strings, each of about ``limit`` bytes."""
    start = size = 0
    for i, text in enumerate(texts):
        if size and size + len(text) > limit:
            yield start, i
            start, size = i, 0
        size += len(text)
    if start < len(texts):
        yield start, len(texts)
