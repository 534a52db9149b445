"""The experiment: draws of variables, three ways of grouping, measures and tests."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.functions import significance
from vpatterns.operators.prepare import cut, cutoff
from vpatterns.plans.draws import STRATEGIES, drawn, measured
from vpatterns.sources.workloads import Matrix

SIZES, RUNS = (4, 8, 12, 16, 20), 10
SCHEMA = "dataset string, n_vars int, run int, strategy string, metric string, value double"


def draw_signatures(matrix: Matrix, draws: list[tuple[int, int]], names: list[list[str]]) -> DataFrame:
    """draw, mask, w: the weighted rows of all draws from one pass over the cells.

    Every cell carries its bit in each draw, so a row's masks are all made by one aggregation.
    """
    spark = matrix.cells.sparkSession
    of_item: dict[str, list[int]] = {}
    for k, some in enumerate(names):
        for i, item in enumerate(some):
            of_item.setdefault(item, [0] * len(draws))[k] = 1 << i
    table = spark.createDataFrame(list(of_item.items()), "item string, bits array<long>")
    rows = matrix.cells.join(F.broadcast(table), "item").groupBy("obs").agg(*[F.bit_or(F.get("bits", F.lit(k))).alias(f"m{k}") for k in range(len(draws))])
    each = rows.select(F.posexplode(F.array(*[f"m{k}" for k in range(len(draws))])).alias("draw", "mask")).where("mask <> 0")
    return each.groupBy("draw", "mask").agg(F.count(F.lit(1)).alias("w"))


def run_experiment(name: str, matrix: Matrix, min_sup: float, sizes=SIZES, runs: int = RUNS, cap: int = 4, strategies=STRATEGIES, linkage: str = "average") -> DataFrame:
    """dataset, n_vars, run, strategy, metric, value: all strategies see the same draws.

    One job makes the weighted rows of all draws, one runs the draws, a task each; a draw's
    rows are at most 2**n_vars masks, however many observations there are. The result is
    written, so times are read once and stay.
    """
    spark = matrix.cells.sparkSession
    least = cutoff(min_sup, matrix.n_obs)
    cells = Matrix(cut(matrix.cells), matrix.n_obs)
    items = sorted(r["item"] for r in cells.cells.select("item").distinct().collect())
    draws = [(size, run) for size in sizes for run in range(runs)]
    names = [drawn(items, size, run) for size, run in draws]
    if not items:
        return spark.createDataFrame([], SCHEMA)
    n_obs = matrix.n_obs

    def one(key, rows):
        k = key[0].as_py()
        masks, w = rows.column("mask").to_numpy(), rows.column("w").to_numpy()
        got = measured(masks, w, names[k], n_obs, least, cap, strategies, linkage)
        columns = [[name] * len(got), [draws[k][0]] * len(got), [draws[k][1]] * len(got), *zip(*got)]
        return pa.table([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int32(), pa.int32(), pa.string(), pa.string(), pa.float64()))], ["dataset", "n_vars", "run", "strategy", "metric", "value"])

    sig = draw_signatures(cells, draws, names)
    return cut(sig.repartition(len(draws), "draw").groupBy("draw").applyInArrow(one, SCHEMA))


def pattern_counts(runs: DataFrame) -> DataFrame:
    """Mean and deviation of the number of patterns by size, beside the largest possible number."""
    got = runs.where("metric = 'patterns' and strategy = 'similar'")
    return got.groupBy("dataset", "n_vars").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd")).withColumn("bound", F.expr("pow(2, n_vars) - 1"))


def series(runs: DataFrame) -> DataFrame:
    """The four curves: whole time, merge time, mean support and mean length before the merge."""
    some = runs.where(F.col("metric").isin("whole_s", "merge_s", "mean_support", "mean_length"))
    return some.groupBy("dataset", "metric", "strategy", "n_vars").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"))


def time_tests(runs: DataFrame, metrics=("merge_s", "whole_s")) -> DataFrame:
    """pair, dataset, metric, t, df, p_less, p_greater: similar against each other strategy, runs paired."""
    some = runs.where(F.col("metric").isin(*metrics))
    mine = some.where("strategy = 'similar'").select("dataset", "n_vars", "run", "metric", F.col("value").alias("x"))
    other = some.where("strategy <> 'similar'").select("dataset", "n_vars", "run", "metric", F.col("strategy").alias("against"), F.col("value").alias("y"))
    return significance.paired_ttest(mine.join(other, ["dataset", "n_vars", "run", "metric"]), "x", "y", ["against", "dataset", "metric"])


def extension_rate(local: DataFrame, final: DataFrame) -> DataFrame:
    """rate: share of local patterns that the merge enlarges (no final pattern is equal)."""
    kept = local.join(final.select("mask").distinct(), "mask", "left_semi")
    return local.agg(F.count(F.lit(1)).alias("n")).crossJoin(kept.agg(F.count(F.lit(1)).alias("k"))).select((1 - F.col("k") / F.nullif(F.col("n"), F.lit(0))).alias("rate"))


def planted_recovery(found: DataFrame, truth: DataFrame, key: str = "vars") -> DataFrame:
    """plant, best: the largest Jaccard index of a planted variable set with a found one."""
    pair = truth.select("plant", F.col(key).alias("t")).crossJoin(F.broadcast(found.select(F.col(key).alias("f"))))
    score = F.size(F.array_intersect("t", "f")) / F.size(F.array_union("t", "f"))
    return pair.groupBy("plant").agg(F.max(score).alias("best"))


def cell_recovery(rows: DataFrame, key: list[str], planted: DataFrame, truth: list[int], name: str) -> DataFrame:
    """plant, best: the largest Jaccard index of the plant's cells with a found pattern's cells.

    ``rows``: obs and the pattern's columns ``key``, its variables being the first of them;
    ``planted``: obs of the plant, its cells being those of the variables ``truth``.
    """
    met = rows.join(planted.select("obs", F.lit(1).alias("own")), "obs", "left")
    each = met.groupBy(*key).agg(F.count(F.lit(1)).alias("n"), F.count("own").alias("hit"))
    size = F.lit(planted.count() * len(truth))
    variables = F.array(*[F.lit(v) for v in truth])
    common = F.col("hit") * F.size(F.array_intersect(F.col(key[0]), variables))
    return each.agg(F.round(F.max(common / (F.col("n") * F.size(key[0]) + size - common)), 6).alias("best")).select(F.lit(name).alias("plant"), "best")
