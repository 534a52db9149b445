"""Significance of patterns and tests of measures: binomial tails and Student's t."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def incomplete_beta(x: float, a: float, b: float) -> float:
    """Regularised incomplete beta function by its continued fraction."""
    if x <= 0:
        return 0.0
    if x >= 1:
        return 1.0
    if x > (a + 1) / (a + b + 2):
        return 1 - incomplete_beta(1 - x, b, a)
    front = math.exp(a * math.log(x) + b * math.log1p(-x) + math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b)) / a
    tiny, c = 1e-300, 1.0
    d = 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    h = d
    for m in range(1, 10_000):
        for k in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + k * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + k / c
            c = c if abs(c) > tiny else tiny
            h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return front * h


def binomial_tail(support: int, n: int, p: float) -> float:
    """Chance of ``support`` or more of n rows to hold a pattern of chance p."""
    if support <= 0:
        return 1.0
    if support > n or p <= 0:
        return 0.0
    return incomplete_beta(p, support, n - support + 1)


def min_support(n_obs: int, item_prob: float, length: int = 4, alpha: float = 0.05) -> int:
    """Least count at which a pattern of ``length`` uniform items is significant, by bisection."""
    p, low, high = item_prob**length, 0, n_obs + 1
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (low, mid) if binomial_tail(mid, n_obs, p) <= alpha else (mid, high)
    return high


def item_probability(cells: DataFrame, n_obs: int) -> float:
    """Chance of an item if all were alike: the share of present cells (obs, item)."""
    got = cells.agg(F.count(F.lit(1)).alias("c"), F.count_distinct("item").alias("m")).first()
    return got["c"] / (n_obs * got["m"]) if n_obs and got["m"] else 0.0


def item_probabilities(cells: DataFrame, n_obs: int) -> DataFrame:
    """item, p: each item's own share of the observations."""
    return cells.groupBy("item").agg((F.count(F.lit(1)) / n_obs).alias("p"))


def t_cdf(t: float, df: float) -> float:
    tail = incomplete_beta(df / (df + t * t), df / 2, 0.5) / 2
    return 1 - tail if t > 0 else tail


@F.pandas_udf(DoubleType())
def binomial_tail_udf(support: pd.Series, n: pd.Series, p: pd.Series) -> pd.Series:
    return pd.Series([binomial_tail(int(s), int(m), float(q)) for s, m, q in zip(support, n, p)])


@F.pandas_udf(DoubleType())
def t_cdf_udf(t: pd.Series, df: pd.Series) -> pd.Series:
    return pd.Series([None if pd.isna(a) else t_cdf(float(a), float(b)) for a, b in zip(t, df)])


def pattern_pvalue(patterns: DataFrame, n_obs: int, probability) -> DataFrame:
    """With p_value: the upper binomial tail of each pattern's support."""
    return patterns.withColumn("p_value", binomial_tail_udf("support", F.lit(n_obs), probability))


def holm(tests: DataFrame, p: str = "p_value") -> DataFrame:
    """With holm and bonferroni: adjusted for all rows; the tests are a small table."""
    order = W.orderBy(p, *[c for c in tests.columns if c != p])
    m = F.count(F.lit(1)).over(W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    step = tests.withColumn("m", m).withColumn("k", F.row_number().over(order))
    step = step.withColumn("h", (F.col("m") - F.col("k") + 1) * F.col(p))
    return step.withColumn("holm", F.least(F.lit(1.0), F.max("h").over(order.rowsBetween(W.unboundedPreceding, 0)))).withColumn("bonferroni", F.least(F.lit(1.0), F.col("m") * F.col(p))).drop("m", "k", "h")


def paired_ttest(rows: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    """by, t, df, p_less, p_greater of the mean of x - y; no spread gives null."""
    d = F.col(x) - F.col(y)
    s = rows.groupBy(*by).agg(F.avg(d).alias("m"), F.stddev_samp(d).alias("sd"), F.count(d).alias("n"))
    s = s.withColumn("t", F.when(F.col("sd") > 0, F.col("m") / (F.col("sd") / F.sqrt(F.col("n").cast("double")))))
    s = s.withColumn("df", (F.col("n") - 1).cast("int")).withColumn("p_less", t_cdf_udf("t", "df"))
    return s.select(*by, "t", "df", "p_less", (1 - F.col("p_less")).alias("p_greater"))


def independent_ttest(rows: DataFrame, value: str, group: str, first: str, second: str, equal: bool = False) -> DataFrame:
    """t, df, p_less, p_greater of two groups, with equal variances or after Welch."""
    part = lambda g: rows.where(F.col(group) == g).agg(F.avg(value).alias("m"), F.var_samp(value).alias("v"), F.count(value).alias("n"))
    both = part(first).toDF("m1", "v1", "n1").crossJoin(part(second).toDF("m2", "v2", "n2"))
    if equal:
        both = both.withColumn("df", F.col("n1") + F.col("n2") - 2.0).withColumn("se", F.expr("sqrt(((n1 - 1) * v1 + (n2 - 1) * v2) / (n1 + n2 - 2) * (1 / n1 + 1 / n2))"))
    else:
        both = both.withColumn("se", F.expr("sqrt(v1 / n1 + v2 / n2)")).withColumn("df", F.expr("pow(v1 / n1 + v2 / n2, 2) / (pow(v1 / n1, 2) / (n1 - 1) + pow(v2 / n2, 2) / (n2 - 1))"))
    both = both.withColumn("t", (F.col("m1") - F.col("m2")) / F.col("se")).withColumn("p_less", t_cdf_udf("t", "df"))
    return both.select("t", "df", "p_less", (1 - F.col("p_less")).alias("p_greater"))
