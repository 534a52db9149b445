"""The methods for SQL users: functions and table functions under vp_ names."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

from vpatterns.functions.significance import binomial_tail_udf, t_cdf_udf
from vpatterns.operators.clustering import fuse


def pattern_sim(y1: pd.Series, y2: pd.Series) -> float:
    """Purity times concentration of two columns; for groups that fit a task's memory."""
    pair = pd.DataFrame({"a": y1.to_numpy(), "b": y2.to_numpy()}).dropna()
    n = len(y1)
    if n < 2 or pair.empty:
        return 0.0
    joint = pair.groupby(["a", "b"]).size()
    first, second = y1.value_counts(), y2.value_counts()
    top = np.maximum(first.reindex(joint.index.get_level_values(0)).to_numpy(), second.reindex(joint.index.get_level_values(1)).to_numpy())
    p = joint.to_numpy() / n
    return float(np.mean(joint.to_numpy() / top) * (1 + np.sum(p * np.log(p)) / np.log(n)))


class FrequentPatterns:
    """mask, support of a table (mask, w) by level-wise search; a partition has 2**cap rows at most."""

    def __init__(self):
        self.rows: list[tuple[int, int]] = []

    def eval(self, row, least: int):
        self.least = least
        self.rows.append((row["mask"], row["w"]))

    def terminate(self):
        level = sorted({1 << i for m, _ in self.rows for i in range(62) if m >> i & 1})
        while level:
            kept = {}
            for c in level:
                s = sum(w for m, w in self.rows if m & c == c)
                if s >= self.least:
                    kept[c] = s
                    yield c, s
            size = level[0].bit_count() + 1
            level = sorted({a | b for a, b in combinations(kept, 2) if (a | b).bit_count() == size})


class Clusters:
    """var_id, cluster_id of a table (a, b, sim) of one partition, none above the cap."""

    def __init__(self):
        self.pairs: dict[tuple[int, int], float] = {}

    def eval(self, row, cap: int):
        self.cap = cap
        self.pairs[(row["a"], row["b"])] = row["sim"]

    def terminate(self):
        if self.pairs:
            home, _ = fuse(self.pairs, sorted({v for p in self.pairs for v in p}), self.cap)
            yield from sorted(home.items())


def register(spark: SparkSession) -> None:
    spark.udf.register("vp_pattern_sim", pandas_udf(pattern_sim, DoubleType()))
    spark.udf.register("vp_binomial_tail", binomial_tail_udf)
    spark.udf.register("vp_t_cdf", t_cdf_udf)
    spark.udtf.register("vp_frequent_patterns", udtf(FrequentPatterns, returnType="mask: long, support: long"))
    spark.udtf.register("vp_clusters", udtf(Clusters, returnType="var_id: int, cluster_id: int"))
