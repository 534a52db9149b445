"""Sources and sinks around the methods: typed reads, basket files, idempotent writes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; only the columns that a plan uses are read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_baskets(spark: SparkSession, path: str, separator: str = r"\s+") -> DataFrame:
    """obs, item from a text file with one basket a line; empty lines have no item.

    An observation's id is unique, not consecutive, and stays the same while the files do.
    """
    lines = spark.read.text(path).withColumn("obs", F.monotonically_increasing_id())
    items = lines.select("obs", F.explode(F.split(F.trim("value"), separator)).alias("item"))
    return items.where("item <> ''").distinct()


def read_typed(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet with an explicit schema: nothing is inferred from the data."""
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def read_jdbc(spark: SparkSession, url: str, dbtable: str, **options) -> DataFrame:
    return spark.read.format("jdbc").options(url=url, dbtable=dbtable, **options).load()


def write_run(df: DataFrame, path: str, run_id: str, partition: str = "run_id") -> None:
    """Rows of one run; writing the same run again replaces it and nothing else."""
    out = df.withColumn(partition, F.lit(run_id))
    out.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(partition).parquet(path)


def small(df: DataFrame, limit: int = 100_000):
    """The rows as an Arrow table, refused beyond ``limit`` rows instead of cut off."""
    got = df.limit(limit + 1).toArrow()
    if got.num_rows > limit:
        raise ValueError(f"more than {limit} rows; write them instead")
    return got
