"""Quality rules: robust multivariate outliers by minimum covariance determinant.

Each text gets word, symbol, line and repetition counts. Their transformed vector is
fitted per language and source: from coordinatewise medians, concentration steps keep
the h nearest rows of each group by Mahalanobis distance and fit mean and covariance
to them again. A step is one aggregation over (group, distance range) that adds up
counts, sums and products, so a group of any size is fitted without being gathered.
The covariance gets the usual consistency factor and a floor, since most texts have
none of some counts and an exact fit would reject the first that has one.

Shares are drawn towards a constant as if the text had ``PRIOR`` more words, or a short
clean text would lie far from its group for its length alone.

Defined cases: null and empty texts have zero counts and fail the base rule; null
languages and sources are groups of their own; a group of one row keeps it; repeated
rows agree; other columns are not read.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.llm.common import documents, scratch, written

#: Fixed values of the base rules.
SYMBOLS, BLANKS = "#*$%&|<>", " \t\n\x0b\x0c\r"
WINDOW = 5
PRIOR, FLOOR = 100.0, 0.05
#: Part of a group that a concentration step keeps, steps, and the tail that is rejected.
KEEP, STEPS, TAIL = 0.75, 5, 1e-5
NAMES = ["length", "symbol", "line", "repeat"]


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words in windows that are found twice or more."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    ids = np.fromiter(map(hash, words), np.int64, len(words)).astype(np.uint64)
    h = ids[:n].copy()
    for i in range(1, window):
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) + ids[i : i + n]
    _, at, times = np.unique(h, return_inverse=True, return_counts=True)
    twice = np.flatnonzero(times[at] > 1)
    if not len(twice):
        return 0
    edges = np.zeros(len(words) + 1, np.int64)
    np.add.at(edges, twice, 1)
    np.add.at(edges, twice + window, -1)
    return int(np.count_nonzero(np.cumsum(edges)[:-1]))


def base_counts(text: str | None) -> tuple[int, int, int, int, int, int]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, lines with a word)."""
    if not text:
        return 0, 0, 0, 0, 0, 0
    words = text.encode("utf-8", "surrogatepass").split()
    lines = [x for x in text.split("\n") if x.strip(BLANKS)]
    return (
        len(words),
        len(text) - sum(map(text.count, BLANKS)),
        sum(map(text.count, SYMBOLS)),
        len(lines) - len(set(lines)),
        repeated_words(words),
        len(lines),
    )


def statistics(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, grp, the base counts and the base rule of every row; no shuffle."""
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines"]

    def step(batches):
        for batch in batches:
            rows = []
            for at in range(0, batch.num_rows, 256):
                rows += map(base_counts, batch.column(2)[at : at + 256].to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, pa.int64()) for c in zip(*rows))], names=[id_col, "grp", *names])

    grp = F.to_json(F.struct("lang", "source"))
    kind = df.schema[id_col].dataType.simpleString()
    out = f"`{id_col}` {kind}, grp string, " + ", ".join(f"{n} long" for n in names)
    got = df.select(id_col, grp.alias("grp"), text_col).mapInArrow(step, out)
    return got.withColumn("base_failed", F.expr("n_words < 10 or 100 * n_repeat_words > 20 * n_words"))


def vectors(stats: DataFrame) -> DataFrame:
    k = F.lit(PRIOR)
    return stats.withColumns({
        "length": F.log((F.col("word_chars") + 5 * k) / (F.col("n_words") + k)),
        "symbol": F.log1p(10 * F.col("n_symbols") / (F.col("n_words") + k)),
        "line": F.col("n_dup_lines") / (F.col("n_lines") + 10.0),
        "repeat": F.col("n_repeat_words") / (F.col("n_words") + k),
    })


def chi2_cdf(x: float, dof: int) -> float:
    """By the series of the lower incomplete gamma function."""
    if x <= 0:
        return 0.0
    a, z = dof / 2, x / 2
    term = total = 1 / a
    for n in range(1, 2000):
        term *= z / (a + n)
        total += term
        if term < total * 1e-15:
            break
    return min(1.0, total * math.exp(-z + a * math.log(z) - math.lgamma(a)))


def chi2_quantile(p: float, dof: int) -> float:
    low, high = 0.0, 1000.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_cdf(mid, dof) < p else (low, mid)
    return high


def _pairs(p: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(p) for j in range(i, p)]


def distance(names: list[str]):
    """Squared Mahalanobis distance from columns mu_i and inv_i_j."""
    d = [F.col(c) - F.col(f"mu_{i}") for i, c in enumerate(names)]
    return sum(((1 if i == j else 2) * F.col(f"inv_{i}_{j}") * d[i] * d[j] for i, j in _pairs(len(names))), F.lit(0.0))


def _fits(moments: DataFrame, p: int, factor: float) -> DataFrame:
    """grp, mu_i, inv_i_j from each group's m, s_i, q_i_j: one row a group."""
    pairs = _pairs(p)
    names = ["grp", *(f"mu_{i}" for i in range(p)), *(f"inv_{i}_{j}" for i, j in pairs)]

    def invert(frames):
        for x in frames:
            rows = []
            for r in x.to_dict("records"):
                m, mean = max(r["m"], 1.0), np.array([r[f"s_{i}"] for i in range(p)]) / max(r["m"], 1.0)
                cov = np.zeros((p, p))
                for i, j in pairs:
                    cov[i, j] = cov[j, i] = r[f"q_{i}_{j}"] / m - mean[i] * mean[j]
                # a floor, and for few rows a pull towards it
                cov = (cov * m * factor + np.eye(p) * FLOOR**2 * 10) / (m + 10) + np.eye(p) * FLOOR**2
                inv = np.linalg.inv(cov)
                rows.append([r["grp"], *mean, *(inv[i, j] for i, j in pairs)])
            yield pd.DataFrame(rows, columns=names)

    return moments.mapInPandas(invert, "grp string, " + ", ".join(f"{n} double" for n in names[1:]))


#: Groups whose fits every task gets, so that no group's rows meet in one task; a fit has some 200 bytes.
SHARED = 50_000


def _beside(rows: DataFrame, fit: DataFrame, how: str = "inner") -> DataFrame:
    """Rows with their group's fit: sent to all tasks up to a counted number of groups, else by a join."""
    return rows.join(F.broadcast(fit) if fit.count() <= SHARED else fit, "grp", how)


def mcd(rows: DataFrame, folder: str, names: list[str] = NAMES, keep: float = KEEP, steps: int = STEPS) -> DataFrame:
    """Location and inverse scatter of each group of ``rows`` (columns grp and names)."""
    p = len(names)
    pairs = _pairs(p)
    middle = written(rows.groupBy("grp").agg(*[F.percentile_approx(c, 0.5, 1000).alias(f"mu_{i}") for i, c in enumerate(names)]), folder, "middle")
    off = [F.abs(F.col(c) - F.col(f"mu_{i}")) for i, c in enumerate(names)]
    spread = _beside(rows, middle).groupBy("grp").agg(*[F.first(f"mu_{i}").alias(f"mu_{i}") for i in range(p)], *[F.percentile_approx(off[i], 0.5, 1000).alias(f"mad_{i}") for i in range(p)])
    scale = lambda i: F.pow(1.4826 * F.col(f"mad_{i}"), 2) + FLOOR**2
    start = spread.select("grp", *[f"mu_{i}" for i in range(p)], *[(1 / scale(i) if i == j else F.lit(0.0)).alias(f"inv_{i}_{j}") for i, j in pairs])
    fit = written(start, folder, "fit0")
    factor = keep / max(1e-9, chi2_cdf(chi2_quantile(keep, p), p + 2))
    products = [F.sum(F.col(names[i]) * F.col(names[j])).alias(f"q_{i}_{j}") for i, j in pairs]
    for n in range(1, steps + 1):
        near = _beside(rows, fit).withColumn("ring", F.floor(F.log2(1 + distance(names)) * 32).cast("int"))
        rings = near.groupBy("grp", "ring").agg(F.count(F.lit(1)).cast("double").alias("m"), *[F.sum(c).alias(f"s_{i}") for i, c in enumerate(names)], *products)
        all_of, up_to = W.partitionBy("grp"), W.partitionBy("grp").orderBy("ring").rowsBetween(W.unboundedPreceding, -1)
        rings = rings.withColumn("h", F.ceil(keep * F.sum("m").over(all_of))).withColumn("before", F.coalesce(F.sum("m").over(up_to), F.lit(0.0)))
        inner = rings.where("before < h")  # the ring in which the h nearest are complete is the last
        sums = ["m", *(f"s_{i}" for i in range(p)), *(f"q_{i}_{j}" for i, j in pairs)]
        fit = written(_fits(inner.groupBy("grp").agg(*[F.sum(c).alias(c) for c in sums]), p, factor), folder, f"fit{n}")
    return fit


def judged(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", tail: float = TAIL) -> DataFrame:
    """Counts, base rule, squared distance and verdict of every row."""
    folder = scratch(df.sparkSession)
    stats = written(statistics(df, id_col, text_col), folder, "stats")
    rows = vectors(stats)
    fit = mcd(rows.where("not base_failed"), folder)
    limit = chi2_quantile(1 - tail, len(NAMES))
    scored = _beside(rows, fit, "left").withColumn("distance2", F.coalesce(distance(NAMES), F.lit(0.0)))
    return scored.withColumn("kept", ~F.col("base_failed") & (F.col("distance2") <= limit))


def op3_mcd_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = judged(documents(spark, sf_dir))
    return got.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance2")
