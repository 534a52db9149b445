"""Similarity of variables: how likely two of them share a pattern, and classical measures.

All work on counts of joint levels: (a, b, la, lb, c). They come from cells joined to
themselves on the observation, from weighted signatures, or from block Gram products;
what follows has a size that depends on variables and levels only.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators.coherence import ratio
from vpatterns.operators.prepare import weight

#: What a joint level with a missing side is: no pair, one more level, or outside N.
POLICIES = ("skip", "level", "pairwise")
#: The level that stands for a missing cell under ``level``.
MISSING = -1


def joint_counts(cells: DataFrame) -> DataFrame:
    """a, b, la, lb, c from cells (obs, var_id, level, w if weighted): one self-join on the observation."""
    x = cells.select("obs", F.col("var_id").alias("a"), F.col("level").alias("la"), weight(cells).alias("w"))
    y = cells.select("obs", F.col("var_id").alias("b"), F.col("level").alias("lb"))
    return x.join(y, "obs").where("a < b").groupBy("a", "b", "la", "lb").agg(F.sum("w").alias("c"))


def joint_counts_of_signatures(sig: DataFrame) -> DataFrame:
    """The same from mask, w: pairs are made inside each distinct row, no self-join."""
    places = F.filter(F.sequence(F.lit(0), F.lit(61)), lambda i: F.getbit("mask", i) == 1)
    one = sig.select("w", places.alias("p")).select("w", "p", F.explode("p").alias("a"))
    pair = one.select("w", "a", F.explode(F.filter("p", lambda x: x > F.col("a"))).alias("b"))
    return pair.groupBy("a", "b").agg(F.sum("w").alias("c")).select("a", "b", F.lit(1).alias("la"), F.lit(1).alias("lb"), "c")


def joint_counts_gram(cells: DataFrame, columns: list[tuple[int, int]], rows_each: int = 4096) -> DataFrame:
    """The same by Gram products of one-hot rows in blocks of columns; ``columns`` lists (var_id, level)."""
    spark = cells.sparkSession
    n = len(columns)
    place = spark.createDataFrame([(v, k, i) for i, (v, k) in enumerate(columns)], "var_id int, level int, place int")
    starts = range(0, n, BLOCK)

    def step(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, rows_each):
                lists = batch.column(0).slice(at, rows_each)
                row = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
                hot = np.zeros((len(lists), n), np.float32)  # counts of a slice are exact in it
                hot[row, lists.flatten().to_numpy()] = 1
                for p in starts:
                    for q in starts:
                        if q >= p:
                            got = (hot[:, p : p + BLOCK].T @ hot[:, q : q + BLOCK]).astype(np.int64)
                            if got.any():
                                total[p, q] = total[p, q] + got if (p, q) in total else got
        for (p, q), t in total.items():
            i, j = np.nonzero(np.triu(t) if p == q else t)  # each pair of columns once
            yield pa.RecordBatch.from_arrays([pa.array(i + p), pa.array(j + q), pa.array(t[i, j])], names=["i", "j", "c"])

    rows = cells.join(F.broadcast(place), ["var_id", "level"]).groupBy("obs").agg(F.collect_list("place").alias("row")).select("row")
    got = rows.mapInArrow(step, "i long, j long, c long").groupBy("i", "j").agg(F.sum("c").alias("c"))
    a, b = place.select(F.col("place").alias("i"), F.col("var_id").alias("a"), F.col("level").alias("la")), place.select(F.col("place").alias("j"), F.col("var_id").alias("b"), F.col("level").alias("lb"))
    met = got.join(F.broadcast(a), "i").join(F.broadcast(b), "j")
    flip = met.where("a > b").select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("lb").alias("la"), F.col("la").alias("lb"), "c")
    return met.where("a < b").select("a", "b", "la", "lb", "c").unionByName(flip)


def marginals(cells: DataFrame) -> DataFrame:
    return cells.groupBy(F.col("var_id").alias("v"), F.col("level").alias("l")).agg(F.sum(weight(cells)).alias("c"))


def marginals_of_signatures(sig: DataFrame) -> DataFrame:
    places = F.filter(F.sequence(F.lit(0), F.lit(61)), lambda i: F.getbit("mask", i) == 1)
    return sig.select("w", F.explode(places).alias("v")).groupBy("v").agg(F.sum("w").alias("c")).select("v", F.lit(1).alias("l"), "c")


def with_missing(joint: DataFrame, single: DataFrame, n_obs: int) -> tuple[DataFrame, DataFrame]:
    """Counts in which a missing cell is one more level, derived without a grid of rows."""
    v = single.groupBy("v").agg(F.sum("c").alias("c")).select("v", F.lit(MISSING).alias("l"), (F.lit(n_obs) - F.col("c")).alias("c"))
    grid = single.select(F.col("v").alias("a")).distinct().crossJoin(F.broadcast(single.select(F.col("v").alias("b")).distinct())).where("a < b")
    left = grid.join(single.select(F.col("v").alias("a"), F.col("l").alias("la"), F.col("c").alias("all")), "a")
    met = joint.groupBy("a", "b", "la").agg(F.sum("c").alias("met"))
    left = left.join(met, ["a", "b", "la"], "left").select("a", "b", "la", F.lit(MISSING).alias("lb"), (F.col("all") - F.coalesce("met", F.lit(0))).alias("c"))
    right = grid.join(single.select(F.col("v").alias("b"), F.col("l").alias("lb"), F.col("c").alias("all")), "b")
    met = joint.groupBy("a", "b", "lb").agg(F.sum("c").alias("met"))
    right = right.join(met, ["a", "b", "lb"], "left").select("a", "b", F.lit(MISSING).alias("la"), "lb", (F.col("all") - F.coalesce("met", F.lit(0))).alias("c"))
    some = joint.unionByName(left).unionByName(right)
    none = grid.join(some.groupBy("a", "b").agg(F.sum("c").alias("s")), ["a", "b"], "left").select("a", "b", F.lit(MISSING).alias("la"), F.lit(MISSING).alias("lb"), (F.lit(n_obs) - F.coalesce("s", F.lit(0))).alias("c"))
    return some.unionByName(none).where("c > 0"), single.unionByName(v).where("c > 0")


def pattern_similarity(joint: DataFrame, single: DataFrame, n_obs: int, missing: str = "skip") -> DataFrame:
    """a, b, purity, concentration, sim of every pair of variables.

    purity is the mean, over distinct joint levels, of the joint count over the larger of
    the two single counts; concentration is one less the entropy of the joint levels over
    that of n_obs distinct rows. Pairs that never meet have 0.
    """
    if missing not in POLICIES:
        raise ValueError(f"missing must be one of {POLICIES}")
    ids = single.select("v").distinct()
    grid = ids.select(F.col("v").alias("a")).crossJoin(F.broadcast(ids.select(F.col("v").alias("b")))).where("a < b")
    if missing == "level":
        joint, single = with_missing(joint, single, n_obs)
    if missing == "pairwise":
        first = joint.groupBy("a", "b", "la").agg(F.sum("c").alias("ca"))
        second = joint.groupBy("a", "b", "lb").agg(F.sum("c").alias("cb"))
        rows = joint.join(first, ["a", "b", "la"]).join(second, ["a", "b", "lb"])
        rows = rows.join(joint.groupBy("a", "b").agg(F.sum("c").alias("n")), ["a", "b"])
    else:
        first = single.select(F.col("v").alias("a"), F.col("l").alias("la"), F.col("c").alias("ca"))
        second = single.select(F.col("v").alias("b"), F.col("l").alias("lb"), F.col("c").alias("cb"))
        rows = joint.join(first, ["a", "la"]).join(second, ["b", "lb"]).withColumn("n", F.lit(n_obs))
    p = F.col("c") / F.col("n")
    scored = rows.groupBy("a", "b").agg(F.avg(F.col("c") / F.greatest("ca", "cb")).alias("purity"), F.sum(p * F.log(p)).alias("e"), F.max("n").alias("n"))
    scored = scored.withColumn("concentration", F.when(F.col("n") > 1, 1 + F.col("e") / F.log(F.col("n").cast("double"))).otherwise(0.0))
    scored = grid.join(scored, ["a", "b"], "left")
    keep = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    return scored.select(F.col("a").cast("int").alias("a"), F.col("b").cast("int").alias("b"), keep("purity").alias("purity"), keep("concentration").alias("concentration"), (keep("purity") * keep("concentration")).alias("sim"))


SIGNS = ("all", "positive", "split")


def difference_similarity(values: DataFrame, n_obs: int, kind: str = "additive", sign_policy: str = "all") -> DataFrame:
    """The same for additive or multiplicative coherence, from whole-number values (obs, var, value).

    A pair of variables is turned into (0, difference) or (1, ratio). Ratios of whole
    numbers are one double for each reduced fraction (``coherence.ratio``); zeros have no
    ratio. ``sign_policy`` of ratios: all, of positive values only, or with the sign of the
    first value as part of the level. Pairs that never meet have 0.
    """
    if sign_policy not in SIGNS:
        raise ValueError(f"sign_policy must be one of {SIGNS}")
    x, y = values.select("obs", F.col("var").alias("a"), F.col("value").alias("x")), values.select("obs", F.col("var").alias("b"), F.col("value").alias("y"))
    both = x.join(y, "obs").where("a < b").withColumn("side", F.lit(0))
    if kind == "additive":
        both = both.withColumn("d", (F.col("y") - F.col("x")).cast("double"))
    else:
        both = both.where("x <> 0 and y <> 0" if sign_policy != "positive" else "x > 0 and y > 0").withColumn("d", ratio("y", "x"))
        both = both.withColumn("side", F.signum("x").cast("int")) if sign_policy == "split" else both
    counts = both.groupBy("a", "b", "side", "d").agg(F.count(F.lit(1)).alias("c"))
    # (0, difference): the first value is one level for all pairs of a side, so the larger share is the side's
    of_side = counts.groupBy("a", "b", "side").agg(F.sum("c").alias("all"), F.count(F.lit(1)).alias("m"), F.sum((F.col("c") / n_obs) * F.log(F.col("c") / n_obs)).alias("e"))
    pair = of_side.groupBy("a", "b").agg(F.count(F.lit(1)).alias("sides"), F.sum("m").alias("m"), F.sum("e").alias("e"))
    purity = F.col("sides") / F.col("m")
    concentration = 1 + F.col("e") / math.log(n_obs) if n_obs > 1 else F.lit(0.0)
    ids = values.select("var").distinct()
    grid = ids.select(F.col("var").alias("a")).join(ids.select(F.col("var").alias("b")), F.col("a") < F.col("b"))
    scored = grid.join(pair.select("a", "b", purity.alias("purity"), concentration.alias("concentration")), ["a", "b"], "left")
    keep = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    return scored.select(F.col("a").cast("int").alias("a"), F.col("b").cast("int").alias("b"), keep("purity").alias("purity"), keep("concentration").alias("concentration"), (keep("purity") * keep("concentration")).alias("sim"))


#: Variables whose pairs are expressions of one aggregation; more are counted in blocks.
EXPRESSIONS = 24
BLOCK = 128


def _pair_blocks(df: DataFrame, columns: list[str], count, kinds: int) -> DataFrame:
    """i, j, s0.. : sums over rows of ``count(x, y)`` for blocks of columns, added across partitions.

    A task holds one block of results at a time for the rows of one batch; what it sends
    are blocks, so the plan has one row a block, not an expression a pair.
    """
    m = len(columns)
    starts = list(range(0, m, BLOCK))

    def step(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            x = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False).astype(float) for i in range(m)])
            for p in starts:
                for q in starts:
                    if q >= p:
                        got = count(x[:, p : p + BLOCK], x[:, q : q + BLOCK])
                        total[p, q] = total[p, q] + got if (p, q) in total else got
        for (p, q), t in total.items():
            i, j = np.meshgrid(np.arange(p, p + t.shape[1]), np.arange(q, q + t.shape[2]), indexing="ij")
            some = i < j
            yield pa.RecordBatch.from_arrays([pa.array(i[some].astype(np.int32)), pa.array(j[some].astype(np.int32)), *(pa.array(t[k][some].astype(float)) for k in range(kinds))], names=["a", "b", *(f"s{k}" for k in range(kinds))])

    schema = "a int, b int, " + ", ".join(f"s{k} double" for k in range(kinds))
    rows = df.select(*[F.col(c).cast("double").alias(f"c{i}") for i, c in enumerate(columns)]).mapInArrow(step, schema)
    return rows.groupBy("a", "b").agg(*[F.sum(f"s{k}").alias(f"s{k}") for k in range(kinds)])


def order_similarity(df: DataFrame, columns: list[str], n_obs: int | None = None, engine: str | None = None) -> DataFrame:
    """a, b, sim over wide rows: the larger share of rows in which one variable is above the other.

    One scan without a join; ties and missing values add nothing. Few variables are
    expressions (two sums a pair), many are counted in blocks of columns.
    """
    engine = engine or ("expressions" if len(columns) <= EXPRESSIONS else "blocks")
    if engine == "blocks":
        def count(x, y):
            above, below = np.zeros((x.shape[1], y.shape[1])), np.zeros((x.shape[1], y.shape[1]))
            for k in range(x.shape[1]):
                above[k], below[k] = (x[:, k, None] > y).sum(axis=0), (x[:, k, None] < y).sum(axis=0)
            return np.stack([above, below])

        n = n_obs if n_obs else df.count()
        return _pair_blocks(df, columns, count, 2).select("a", "b", (F.greatest("s0", "s1") / n).alias("sim"))
    pairs = [(i, j) for i in range(len(columns)) for j in range(i + 1, len(columns))]
    sums = [F.sum(F.when(F.col(columns[i]) > F.col(columns[j]), 1).otherwise(0)).alias(f"g{i}_{j}") for i, j in pairs]
    sums += [F.sum(F.when(F.col(columns[i]) < F.col(columns[j]), 1).otherwise(0)).alias(f"l{i}_{j}") for i, j in pairs]
    total = df.agg(F.count(F.lit(1)).alias("n"), *sums)
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("a"), F.lit(j).alias("b"), F.greatest(f"g{i}_{j}", f"l{i}_{j}").alias("m")) for i, j in pairs]))
    n = F.lit(n_obs) if n_obs else F.col("n")
    return total.select(each.alias("e"), "n").select("e.a", "e.b", (F.col("e.m") / n).alias("sim"))


def order_similarity_cells(values: DataFrame, n_obs: int) -> DataFrame:
    """The same from cells (obs, var, value); pairs that never meet have 0."""
    x, y = values.select("obs", F.col("var").alias("a"), F.col("value").alias("x")), values.select("obs", F.col("var").alias("b"), F.col("value").alias("y"))
    met = x.join(y, "obs").where("a < b").groupBy("a", "b").agg(F.count_if(F.expr("x > y")).alias("g"), F.count_if(F.expr("x < y")).alias("l"))
    ids = values.select("var").distinct()
    grid = ids.select(F.col("var").alias("a")).join(ids.select(F.col("var").alias("b")), F.col("a") < F.col("b"))
    return grid.join(met, ["a", "b"], "left").select(F.col("a").cast("int").alias("a"), F.col("b").cast("int").alias("b"), (F.coalesce(F.greatest("g", "l"), F.lit(0)) / n_obs).alias("sim"))


def jaccard(joint: DataFrame, single: DataFrame) -> DataFrame:
    """a, b, score: observations where both have one level over those where either is present."""
    n = single.groupBy("v").agg(F.sum("c").alias("c"))
    grid = n.select(F.col("v").alias("a"), F.col("c").alias("na")).crossJoin(F.broadcast(n.select(F.col("v").alias("b"), F.col("c").alias("nb")))).where("a < b")
    met = joint.where("la = lb").groupBy("a", "b").agg(F.sum("c").alias("m"))
    m = F.coalesce("m", F.lit(0))
    return grid.join(met, ["a", "b"], "left").select(F.col("a").cast("int").alias("a"), F.col("b").cast("int").alias("b"), (m / (F.col("na") + F.col("nb") - m)).alias("score"))


def pearson(df: DataFrame, columns: list[str], engine: str | None = None) -> DataFrame:
    """a, b, score; many variables by sums of products in blocks, over rows where both are present.

    The block form moves every variable by its mean first, so the sums keep their digits.
    """
    engine = engine or ("expressions" if len(columns) <= EXPRESSIONS else "blocks")
    if engine == "blocks":
        means = df.agg(*[F.avg(c).alias(f"m{i}") for i, c in enumerate(columns)]).first()
        shift = [float(means[f"m{i}"] or 0.0) for i in range(len(columns))]
        moved = df.select(*[(F.col(c) - F.lit(m)).alias(f"c{i}") for i, (c, m) in enumerate(zip(columns, shift))])

        def count(x, y):
            u, v = (~np.isnan(x)).astype(float), (~np.isnan(y)).astype(float)
            x, y = np.nan_to_num(x), np.nan_to_num(y)
            return np.stack([u.T @ v, x.T @ v, u.T @ y, (x * x).T @ v, u.T @ (y * y), x.T @ y])

        sums = _pair_blocks(moved, [f"c{i}" for i in range(len(columns))], count, 6)
        return sums.select("a", "b", F.expr("(s0 * s5 - s1 * s2) / nullif(sqrt(s0 * s3 - s1 * s1) * sqrt(s0 * s4 - s2 * s2), 0D)").alias("score"))
    pairs = [(i, j) for i in range(len(columns)) for j in range(i + 1, len(columns))]
    total = df.agg(*[F.corr(columns[i], columns[j]).alias(f"r{i}_{j}") for i, j in pairs])
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("a"), F.lit(j).alias("b"), F.col(f"r{i}_{j}").alias("score")) for i, j in pairs]))
    return total.select(each.alias("e")).select("e.a", "e.b", "e.score")


def kendall(joint: DataFrame, form: str = "b") -> DataFrame:
    """a, b, score: rank correlation from joint counts; the work depends on levels, not rows."""
    x, y = joint.alias("x"), joint.alias("y")
    both = x.join(y, (F.col("x.a") == F.col("y.a")) & (F.col("x.b") == F.col("y.b")) & (F.col("x.la") < F.col("y.la")), "inner")
    sign = F.signum(F.col("y.lb").cast("double") - F.col("x.lb"))
    s = both.groupBy(F.col("x.a").alias("a"), F.col("x.b").alias("b")).agg(F.sum(sign * F.col("x.c") * F.col("y.c")).alias("s"))
    half = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2.0)
    n = joint.groupBy("a", "b").agg(F.sum("c").alias("n"))
    t1 = joint.groupBy("a", "b", "la").agg(F.sum("c").alias("c")).groupBy("a", "b").agg(half("c").alias("n1"))
    t2 = joint.groupBy("a", "b", "lb").agg(F.sum("c").alias("c")).groupBy("a", "b").agg(half("c").alias("n2"))
    rows = n.join(t1, ["a", "b"]).join(t2, ["a", "b"]).join(s, ["a", "b"], "left").withColumn("s", F.coalesce("s", F.lit(0.0)))
    n0 = F.col("n") * (F.col("n") - 1) / 2.0
    below = n0 if form == "a" else F.sqrt((n0 - F.col("n1")) * (n0 - F.col("n2")))
    return rows.select(F.col("a").cast("int").alias("a"), F.col("b").cast("int").alias("b"), (F.col("s") / F.nullif(below, F.lit(0.0))).alias("score"))


def partner_counts(joint: DataFrame) -> DataFrame:
    """a, b, la, partners: with how many levels of b each level of a is matched."""
    return joint.groupBy("a", "b", "la").agg(F.count_distinct("lb").alias("partners"))
