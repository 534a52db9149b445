"""The corpus pipeline: language, near duplicates, repeats, mix, tokens.

Every stage works on all rows that the stage before it kept. Rows with a null doc_id pass
the near-duplicate stage, since no class can be named after them. ``ORACLE_SQL`` is None:
four of the stages have no form in SQL; tests compare each with a brute-force version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.llm import bpe, jaccard, langid, mixing, repeats
from vpatterns.llm.common import documents, scratch, written

ORACLE_SQL = None


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without letters go, and texts in which no language stands out."""
    langs, table = langid.build_filter(langid.training_rows(docs))
    return langid.accepted(docs, langs, table)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of near duplicates the document with the least id stays.

    Of rows that share an id the least stays, by all columns that have an order, so reruns agree.
    """
    stays = jaccard.classes(docs).where("doc_id = component_id").select(F.col("doc_id").alias("_id")).distinct()
    # a row travels as one value, so no column of it can clash
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    ordered = F.struct(*[F.col(f"`{f.name}`") for f in docs.schema if not f.dataType.simpleString().startswith(("map", "variant"))])
    kept = docs.select(F.col("doc_id").alias("_id"), row.alias("_row"), ordered.alias("_order")).join(stays, "_id", "left_semi")
    one = kept.groupBy("_id").agg(F.min_by("_row", "_order").alias("_row"))
    return one.select("_row.*").unionByName(docs.where("doc_id is null"))


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that stand elsewhere too are cut out of the texts."""
    out = repeats.cleaned(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def mixing_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources in their target shares: documents go, or come twice."""
    return mixing.mixed(docs)


def bpe_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text."""
    got = bpe.encode(docs, bpe.default_tokenizer())
    return got.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("mixing", mixing_sources),
    ("bpe_encoding", bpe_encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the documents; each result is written and read again."""
    folder, docs = scratch(spark), documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), folder, name)
    return STAGES[-1][1](spark, docs, sf_dir)
