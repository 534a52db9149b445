"""Closed frequent patterns of any number of variables, each made once.

A closed pattern grows by one later variable and is closed again over its rows; the result
counts only if closing added nothing before that variable, so no pattern is made twice and
nothing is compared or stored beside the path. Work is dealt out by the first two variables.

Few frequent variables can have nearly as many closed patterns as there are masks. Up to
``DENSE`` of them, every support comes from sums over supersets instead: a task takes one
choice of the last variables and a table of 2**TABLE entries for the others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators.number import closed_number
from vpatterns.operators.prepare import MASK_BITS, bits, cut, cutoff, weight
from vpatterns.operators.tally import closed_counts
from vpatterns.sources.workloads import Matrix

#: Frequent variables up to which all masks are looked at, and those of one table.
DENSE, TABLE = 26, 18
#: Share of all cells that are present beyond which patterns of more variables are counted without a list.
FULL = 1 / 3


def extended(rows: np.ndarray, w: np.ndarray, first: np.ndarray, last: int, least: float):
    """(pattern, support) of a closed pattern's closed extensions by variables after ``last``.

    ``rows``: presence matrix of the rows that hold the pattern ``first``.
    """
    stack = [(rows, w, first, last)]
    while stack:
        rows, w, have, last = stack.pop()
        joint = (rows * w[:, None]).T @ rows  # weights of all pairs within the pattern's rows
        own = np.diagonal(joint)
        for j in np.flatnonzero((own >= least) & ~have):
            if j <= last:
                continue
            shut = joint[j] == own[j]
            if (shut[:j] & ~have[:j]).any():
                continue
            yield shut, own[j]
            if ((joint[j, j + 1 :] >= least) & ~shut[j + 1 :]).any():
                keep = rows[:, j] > 0
                stack.append((rows[keep], w[keep], shut, j))


def superset_sums(masks: np.ndarray, w: np.ndarray, n: int) -> np.ndarray:
    """Weight of the rows that hold each of 2**n masks, one variable at a time."""
    total = np.bincount(masks, w, 1 << n).astype(np.int64)
    for i in range(n):
        halves = total.reshape(-1, 2, 1 << i)
        halves[:, 0] += halves[:, 1]
    return total


def _dense(rows: DataFrame, m: int, least: int, table: int) -> DataFrame:
    """mask, support of all closed patterns of m variables from rows (mask, w)."""
    low = min(m, table)
    high = m - low
    # a row belongs to every choice of last variables that it holds
    choices = F.sequence(F.lit(0), F.lit((1 << high) - 1))
    top = F.shiftright("mask", low)
    each = rows.withColumn("choice", F.explode(F.filter(choices, lambda c: top.bitwiseAND(c.cast("long")) == c.cast("long"))))

    def one(key, t):
        choice = key[0].as_py()
        masks, w = t.column("mask").to_numpy(), t.column("w").to_numpy()
        own = masks & ((1 << low) - 1)
        total = superset_sums(own, w, low)
        keep = total >= least
        if not choice:
            keep[0] = False  # the empty pattern
        for i in range(low):
            halves, kept = total.reshape(-1, 2, 1 << i), keep.reshape(-1, 2, 1 << i)
            kept[:, 0] &= halves[:, 0] != halves[:, 1]
        for i in range(high):
            if not choice >> i & 1:
                has = (masks >> (low + i) & 1) == 1
                keep &= superset_sums(own[has], w[has], low) != total
        found = np.flatnonzero(keep)
        return pa.table({"mask": pa.array(found | choice << low, pa.int64()), "support": pa.array(total[found])})

    return each.repartition(max(1, 1 << high), "choice").groupBy("choice").applyInArrow(one, "mask long, support long")


def frequent_variables(matrix: Matrix, min_sup: float) -> list[tuple[str, int]]:
    """(item, support) of the frequent variables, the rarest first."""
    counts = matrix.cells.groupBy("item").agg(F.sum(weight(matrix.cells)).alias("f"))
    return [tuple(r) for r in counts.where(F.col("f") >= cutoff(min_sup, matrix.n_obs)).orderBy("f", "item").collect()]


def is_dense(matrix: Matrix, frequent: list[tuple[str, int]]) -> bool:
    return DENSE < len(frequent) <= MASK_BITS and sum(f for _, f in frequent) > FULL * len(frequent) * matrix.n_obs


def distinct_masks(matrix: Matrix, frequent: list[tuple[str, int]]) -> DataFrame:
    """Distinct rows (mask, w) of the frequent variables, the most frequent in the lowest bit."""
    numbers = matrix.cells.sparkSession.createDataFrame([(n, i) for i, (n, _) in enumerate(reversed(frequent))], "item string, v int")
    masks = matrix.cells.join(F.broadcast(numbers), "item").groupBy("obs").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("v"))).alias("mask"), F.first(weight(matrix.cells)).cast("long").alias("w"))
    return cut(masks.groupBy("mask").agg(F.sum("w").alias("w")))


def closed_by_length(matrix: Matrix, min_sup: float) -> DataFrame:
    """n_vars, patterns, least_support, most_support, total_support of all closed frequent patterns.

    Dense matrices have too many of them to list (``tally``); those of all others are listed.
    """
    frequent = frequent_variables(matrix, min_sup)
    if not is_dense(matrix, frequent):
        sums = F.count(F.lit(1)).alias("patterns"), F.min("support").alias("least_support"), F.max("support").alias("most_support"), F.sum("support").alias("total_support")
        return closed_patterns(matrix, min_sup, frequent).groupBy("n_vars").agg(*sums)
    return closed_counts(distinct_masks(matrix, frequent), len(frequent), cutoff(min_sup, matrix.n_obs))


def number_of_closed(matrix: Matrix, min_sup: float) -> int:
    """Number of all closed frequent patterns; those of dense matrices are not made one by one (``number``)."""
    frequent = frequent_variables(matrix, min_sup)
    if not is_dense(matrix, frequent):
        return closed_patterns(matrix, min_sup, frequent).count()
    return closed_number(distinct_masks(matrix, frequent), len(frequent), cutoff(min_sup, matrix.n_obs))


def closed_patterns(matrix: Matrix, min_sup: float, frequent: list[tuple[str, int]] | None = None) -> DataFrame:
    """items (sorted), support, n_vars of all closed frequent patterns over all variables."""
    spark, least = matrix.cells.sparkSession, cutoff(min_sup, matrix.n_obs)
    own = weight(matrix.cells)
    names = [n for n, _ in (frequent_variables(matrix, min_sup) if frequent is None else frequent)]
    m = len(names)
    numbers = spark.createDataFrame([(n, i) for i, n in enumerate(names)], "item string, v int")
    named = F.array(*map(F.lit, names)) if names else F.array().cast("array<string>")
    if 0 < m <= DENSE:
        masks = matrix.cells.join(F.broadcast(numbers), "item").groupBy("obs").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("v"))).alias("mask"), F.first(own).alias("w"))
        found = _dense(cut(masks.groupBy("mask").agg(F.sum("w").alias("w"))), m, least, TABLE)
        return found.select(F.array_sort(F.transform(bits("mask"), lambda v: F.get(named, v))).alias("items"), "support", F.bit_count("mask").cast("int").alias("n_vars"))
    rows = matrix.cells.join(F.broadcast(numbers), "item").groupBy("obs").agg(F.array_sort(F.collect_list("v")).alias("vars"), F.first(own).alias("w"))
    rows = cut(rows.groupBy("vars").agg(F.sum("w").alias("w")))
    first = rows.select("vars", "w", F.explode("vars").alias("i"))
    pairs = first.select("i", "w", F.explode("vars").alias("k")).groupBy("i", "k").agg(F.sum("w").alias("s")).where(F.col("s") >= least).toArrow()
    joint = np.zeros((m, m))
    joint[pairs.column("i").to_numpy(), pairs.column("k").to_numpy()] = pairs.column("s").to_numpy()
    shut = joint == np.diagonal(joint)[:, None]
    roots = [i for i in range(m) if not shut[i, :i].any()]
    # second variables that begin a branch: frequent with the first and not in its closure
    starts = [(i, j) for i in roots for j in range(i + 1, m) if joint[i, j] >= least and not shut[i, j]]
    shared = spark.sparkContext.broadcast((shut, names))

    def branch(key, table):
        shut, names = shared.value
        i, j = (k.as_py() for k in key)
        lists = table.column("vars").combine_chunks()
        at = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
        held = np.zeros((len(lists), len(names)))
        held[at, lists.flatten().to_numpy()] = 1
        w = table.column("w").to_numpy().astype(float)
        have, total = held.all(axis=0), w.sum()
        found = []
        if not (have[:j] & ~shut[i][:j]).any():
            found.append((np.flatnonzero(have).astype(np.int32), total))
            found += [(np.flatnonzero(p).astype(np.int32), s) for p, s in extended(held, w, have, j, least)]
        flat = np.concatenate([p for p, _ in found]) if found else np.zeros(0, np.int32)
        ends = np.cumsum([0, *(len(p) for p, _ in found)]).astype(np.int64)
        got = pa.LargeListArray.from_arrays(pa.array(ends), pa.array(flat)).cast(pa.list_(pa.int32()))
        return pa.table({"p": got, "support": pa.array([int(s) for _, s in found], pa.int64())})

    alone = spark.createDataFrame([([int(k) for k in np.flatnonzero(shut[i])], int(joint[i, i])) for i in roots], "p array<int>, support long")
    asked = spark.createDataFrame(starts, "i int, j int")
    each = first.select("vars", "w", "i", F.explode("vars").alias("j")).where("i < j").join(F.broadcast(asked), ["i", "j"])
    deeper = each.groupBy("i", "j").applyInArrow(branch, "p array<int>, support long")
    return alone.unionByName(deeper).select(F.array_sort(F.transform("p", lambda v: F.get(named, v))).alias("items"), "support", F.size("p").alias("n_vars"))
