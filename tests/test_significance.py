import math

import pytest

from vpatterns.functions import significance as G
from vpatterns.functions.sqlapi import FrequentPatterns


def test_binomial_tail():
    for n, p in ((20, 0.3), (50, 0.07)):
        for k in (0, 1, 5, 12, 20):
            want = sum(math.comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k, n + 1))
            assert G.binomial_tail(k, n, p) == pytest.approx(want, rel=1e-9, abs=1e-14)
    assert G.binomial_tail(21, 20, 0.3) == 0


def test_min_support_is_the_first_significant_count():
    for n, q in ((15000, 0.146), (1000, 0.427), (500, 0.213)):
        k = G.min_support(n, q)
        assert G.binomial_tail(k, n, q**4) <= 0.05 < G.binomial_tail(k - 1, n, q**4)
    assert [G.min_support(n, q) for n, q in ((15000, 0.146), (1000, 0.427), (60000, 0.256), (4006, 0.118), (500, 0.213))] == [12, 44, 285, 3, 4]


def test_t_quantiles():
    for t, df, p in ((6.313752, 1, 0.95), (2.919986, 2, 0.95), (2.131847, 4, 0.95), (1.833113, 9, 0.95), (1.676551, 49, 0.95)):
        assert G.t_cdf(t, df) == pytest.approx(p, abs=1e-6)
        assert G.t_cdf(-t, df) == pytest.approx(1 - p, abs=1e-6)


def test_paired(spark):
    rows = spark.createDataFrame([("p", float(i), i + (0.5 if i % 2 else -0.2)) for i in range(10)] + [("same", 1.0, 1.0)] * 3, "pair string, x double, y double")
    got = {r["pair"]: r for r in G.paired_ttest(rows, "x", "y", ["pair"]).collect()}
    assert got["p"]["df"] == 9 and got["p"]["p_less"] + got["p"]["p_greater"] == pytest.approx(1)
    assert got["same"]["t"] is None


def test_holm(spark):
    got = [(r["holm"], r["bonferroni"]) for r in G.holm(spark.createDataFrame([(0.01,), (0.04,), (0.03,)], "p_value double")).orderBy("p_value").collect()]
    assert got == [(pytest.approx(0.03), pytest.approx(0.03)), (pytest.approx(0.06), pytest.approx(0.09)), (pytest.approx(0.06), pytest.approx(0.12))]


def test_table_function_alone():
    f = FrequentPatterns()
    for m, w in ((0b111, 3), (0b011, 2), (0b100, 1)):
        f.eval({"mask": m, "w": w}, 3)
    assert dict(f.terminate()) == {1: 5, 2: 5, 4: 4, 3: 5, 5: 3, 6: 3, 7: 3}


def test_unpaired_tests(spark):
    import math

    from vpatterns.functions import significance as G

    a, b = [1.0, 2.0, 4.0, 7.0], [3.0, 5.0, 8.0, 9.0, 12.0]
    rows = spark.createDataFrame([("a", x) for x in a] + [("b", x) for x in b] + [("c", 99.0), ("a", None)], "g string, x double")
    mean, var = (lambda x: sum(x) / len(x)), (lambda x: sum((v - sum(x) / len(x)) ** 2 for v in x) / (len(x) - 1))
    va, vb = var(a) / len(a), var(b) / len(b)
    welch = G.independent_ttest(rows, "x", "g", "a", "b").first()
    df = (va + vb) ** 2 / (va**2 / 3 + vb**2 / 4)
    assert welch["t"] == pytest.approx((mean(a) - mean(b)) / math.sqrt(va + vb)) and welch["df"] == pytest.approx(df)

    def by_sums(t, df, steps=200_000):  # the density's integral by the midpoint rule
        c = math.exp(math.lgamma((df + 1) / 2) - math.lgamma(df / 2)) / math.sqrt(df * math.pi)
        h = abs(t) / steps
        half = sum(c * (1 + ((i + 0.5) * h) ** 2 / df) ** (-(df + 1) / 2) for i in range(steps)) * h
        return 0.5 - half if t < 0 else 0.5 + half

    assert welch["p_less"] == pytest.approx(by_sums(welch["t"], df), abs=1e-7)
    assert welch["p_less"] + welch["p_greater"] == pytest.approx(1)
    pooled = (3 * var(a) + 4 * var(b)) / 7
    equal = G.independent_ttest(rows, "x", "g", "a", "b", True).first()
    assert equal["df"] == 7 and equal["t"] == pytest.approx((mean(a) - mean(b)) / math.sqrt(pooled * (1 / 4 + 1 / 5)))
