import pytest
from pyspark.sql import types as T

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


@pytest.fixture(scope="session")
def make(spark):
    """Documents from texts or (text, lang, source); ids count up."""

    def f(rows, **extra):
        full = [(i, *(r if isinstance(r, tuple) else (r, "en", f"s{i % 3}")), len((r[0] if isinstance(r, tuple) else r) or "")) for i, r in enumerate(rows)]
        return spark.createDataFrame(full, DOCS)

    return f


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in every column, empty and long texts, ties and repeated rows, a clashing extra column."""
    long = "word " * 3000 + "x" * 5000
    rows = [(None, None, None, None, None), (1, None, "en", "a", 0), (2, "", None, None, 0), (3, " \n\t ", "en", "a", 4), (4, "the cat", "en", "b", 7), (4, "the cat", "en", "b", 7), (5, "der Hund läuft schnell über die Straße", "de", "b", 38), (6, long, "en", "a", len(long)), (7, "é" * 300, "fr", "c", 300), (None, "no id at all here", "en", "a", 17)]
    return spark.createDataFrame([(*r, 1) for r in rows], T.StructType([*DOCS.fields, T.StructField("score", T.IntegerType())]))


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)
