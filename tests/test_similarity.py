"""Worked similarity examples, blind spot of correlation, properties."""

import math

import pytest
from pyspark.sql import functions as F

from vpatterns.operators import similarity as S

CASES = [
    ("aaaaaa", "zzzzzz", 1, 1),
    ("aaabbb", "xxxyyy", 1, 0.613147),
    ("aabbcc", "xxyyzz", 1, 0.386853),
    ("aaaaaa", "xxxyyy", 0.5, 0.613147),
    ("aaabbb", "xyzxyz", 0.333333, 0),
    ("abcdef", "uvwxyz", 1, 0),
    ("aaabbb", "xxyyyy", 0.555556, 0.435525),
    ("aaabcd", "xxxyzw", 1, 0.306574),
]


def cells(spark, *columns):
    rows = [(i, v, ord(c)) for v, col in enumerate(columns) for i, c in enumerate(col) if c != " "]
    return spark.createDataFrame(rows, "obs long, var_id int, level int")


def scores(c, n, missing="skip"):
    return {(r["a"], r["b"]): r for r in S.pattern_similarity(S.joint_counts(c), S.marginals(c), n, missing).collect()}


@pytest.mark.parametrize("y1,y2,purity,concentration", CASES)
def test_worked_examples(spark, y1, y2, purity, concentration):
    r = scores(cells(spark, y1, y2), 6)[0, 1]
    assert (r["purity"], r["concentration"]) == (pytest.approx(purity, abs=1e-6), pytest.approx(concentration, abs=1e-6))
    assert r["sim"] == pytest.approx(purity * concentration, abs=1e-6)


def test_policies_differ_on_missing_cells(spark):
    c = cells(spark, "11  11  ", "111   11")
    got = {m: scores(c, 8, m)[0, 1]["sim"] for m in S.POLICIES}
    assert got["pairwise"] == pytest.approx(1)
    assert got["skip"] == pytest.approx(2 / 5 * (1 + 0.25 * math.log(0.25) / math.log(8)))
    assert 0 <= got["level"] <= 1 and got["level"] != got["skip"]


def test_no_common_row_and_one_row(spark):
    assert scores(cells(spark, "aa  ", "  bb"), 4)[0, 1]["sim"] == 0
    assert scores(cells(spark, "a", "b"), 1)[0, 1]["sim"] == 0


def test_symmetry_and_relabelling(spark):
    a, b, c = "aabbccaa", "xyxyxxyy", "ppqqppqq"
    one = scores(cells(spark, a, b, c), 8)
    other = scores(cells(spark, b[::-1], a[::-1].replace("a", "k"), c[::-1]), 8)
    assert one[0, 1]["sim"] == pytest.approx(other[0, 1]["sim"])
    assert all(0 <= r["sim"] <= min(r["purity"], r["concentration"]) + 1e-12 for r in one.values())


def test_order_similarity(spark):
    df = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (1, 5), (2, 4), (3, 3), (None, 1)], "x int, y int")
    assert S.order_similarity(df, ["x", "y"], 6).first()["sim"] == pytest.approx(5 / 6)


def test_blind_spot(spark):
    rows = [(i, v, x) for i, p in enumerate([(1, 2), (2, 3), (3, 4), (1, 5), (2, 4), (3, 3)]) for v, x in enumerate(p)]
    values = spark.createDataFrame(rows, "obs long, var int, value long")
    r = S.difference_similarity(values, 6).first()
    assert r["purity"] == 0.25 and r["concentration"] == pytest.approx(0.306574, abs=1e-6)


def test_gram_and_signature_engines_agree(spark):
    c = cells(spark, "11 1 1 1", "1 11  11", " 1111 1 ")
    join = sorted(map(tuple, S.joint_counts(c).select("a", "b", "c").collect()))
    gram = sorted(map(tuple, S.joint_counts_gram(c, [(v, 49) for v in range(3)]).select("a", "b", "c").collect()))
    sig = c.groupBy("obs").agg(F.bit_or(F.expr("shiftleft(1L, var_id)")).alias("mask")).groupBy("mask").agg(F.count("*").alias("w"))
    assert join == gram == sorted(map(tuple, S.joint_counts_of_signatures(sig).select("a", "b", "c").collect()))
