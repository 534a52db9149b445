"""Nulls, empty and very long texts, ties, repeated rows, no rows, clashing extra columns: each operator."""

import pytest
from pyspark.sql import functions as F

from vpatterns.llm import bpe, hmm, jaccard, langid, media, mixing, quality, repeats, tokens, toxicity
from vpatterns.llm.common import remainder

import corpus_pipeline


def run(docs):
    spark = docs.sparkSession
    langs, table = langid.build_filter(langid.training_rows(docs))
    labels = docs.select("doc_id", F.lit(1).alias("quality"), (F.col("doc_id") % 2).cast("int").alias("toxic"))
    return {
        "mix": mixing.plan(docs),
        "lang": langid.identify(docs, langs, table),
        "quality": quality.judged(docs),
        "media": media.stored(docs),
        "jaccard": jaccard.classes(docs),
        "tokens": tokens.attribute(docs, tokens.default_tokenizer()),
        "hmm": hmm.scored(docs, remainder(7) == 2, 2, 2),
        "repeats": repeats.spans_of(docs),
        "bpe": bpe.encode(docs, bpe.default_tokenizer()),
        "toxic": toxicity.scored(docs, toxicity.fit(docs, labels)),
    }


@pytest.fixture(scope="module")
def results(odd):
    """Every operator's rows, made once."""
    return {name: odd.sparkSession.createDataFrame(df.collect(), df.schema).cache() for name, df in run(odd).items()}


def test_each_operator_returns_each_row(odd, results):
    n = odd.count()
    for name, df in results.items():
        assert df.count() == n, name


def test_each_operator_takes_an_empty_table(none):
    for name, df in run(none).items():
        assert df.count() == 0, name


@pytest.mark.parametrize("which", ["odd", "none"])
def test_each_stage(request, spark, which):
    docs = request.getfixturevalue(which)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, docs, "")
        assert got.columns == docs.columns, name
        got.count()
    assert "ids" in corpus_pipeline.STAGES[-1][1](spark, docs, "").columns


def test_defined_results(results):
    got = results
    lang = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in got["lang"].where("doc_id in (1, 2, 3)").collect()}
    assert set(lang.values()) == {("und", 0.0)}
    assert {r["n_shingles"] for r in got["jaccard"].where("doc_id in (1, 2, 3)").collect()} == {0}
    assert {r["component_id"] for r in got["jaccard"].where("doc_id = 4").collect()} == {4}
    assert {r["taken"] for r in got["mix"].where("size = 0").collect()} == {0}
    assert {r["n_bytes"] for r in got["media"].where("doc_id in (1, 2)").collect()} == {0}
    assert {r["payload_bytes"] for r in got["media"].where("doc_id in (1, 2)").collect()} == {64}
    assert {r["n_tokens"] for r in got["hmm"].where("doc_id in (1, 2, 3)").collect()} == {1}
    empty = "doc_id in (1, 2)"
    blank = "doc_id in (1, 2, 3)"
    assert {(r["n_words"], r["base_failed"], r["kept"]) for r in got["quality"].where(blank).collect()} == {(0, True, False)}
    assert {(r["n_tokens"], len(r["sections"])) for r in got["tokens"].where(empty).collect()} == {(0, 0)}
    assert {(tuple(r["ids"]), r["decoded"]) for r in got["bpe"].where(empty).collect()} == {((), "")}
    assert {(r["n_bytes"], len(r["spans"]), bytes(r["kept"])) for r in got["repeats"].where(empty).collect()} == {(0, 0, b"")}
    # repeated rows get one result
    for name, columns in (("quality", ("n_words", "kept")), ("tokens", ("n_tokens",)), ("bpe", ("decoded",)), ("toxic", ("score",)), ("hmm", ("score",)), ("lang", ("lang_pred", "score")), ("media", ("media_sha256",))):
        assert len({tuple(r[c] for c in columns) for r in got[name].where("doc_id = 4").collect()}) == 1, name
    assert len({r["score"] for r in got["toxic"].where(blank).collect()}) == 1
    assert all(0 <= r["score"] <= 1 for r in got["toxic"].collect())
    assert got["hmm"].where("doc_id is null").count() == 2


def test_one_row_of_an_id_stays_and_reruns_agree(spark, make):
    rows = [(5, "one text of five words here", "en", "a", 1), (5, "another text with other words in it", "en", "b", 2), (6, "quite a different thing from both of them", "en", "a", 3)]
    docs = spark.createDataFrame(rows, make([]).schema)
    near = dict(corpus_pipeline.STAGES)["near_duplicates"]
    runs = [sorted((r["doc_id"], r["text"]) for r in near(spark, docs.repartition(n), "").collect()) for n in (1, 3)]
    assert runs[0] == runs[1] == [(5, "another text with other words in it"), (6, rows[2][1])]


def test_names_that_operators_use_themselves(odd):
    docs = odd
    for name in ("_mix_id", "_mix_copies", "_mix_round", "_mix_row", "_row", "_id", "_order", "pack", "start", "token", "grp", "bin"):
        docs = docs.withColumn(name, F.lit(3))
    spark = odd.sparkSession
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, docs, "")
        assert got.columns == docs.columns, name
        assert {r["pack"] for r in got.select("pack").collect()} <= {3}, name
