"""Connected components of a graph of pairs.

Each partition first reduces its own pairs to a spanning forest by union and find, so what
is left has at most one pair a node and partition. A graph whose forest was counted to fit
one task (``IN_ONE`` pairs, 16 bytes each) is finished there; a larger one goes through
alternating star contractions, as DataFrame joins. Both give the least node of a component.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.llm.common import forget, written

#: Pairs that one task finishes at most.
IN_ONE = 2_000_000


def _roots(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the least node of each one's component) of the pairs u, v.

    Whole arrays at a time: every root takes the least root among its neighbours, then all
    paths are halved, until no pair joins two roots.
    """
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        x, y = root[a], root[b]
        open_ = x != y
        if not open_.any():
            return nodes, nodes[root]
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]


def _forest(batches):
    """u, v: every node that is not a root, with its root, of one partition's pairs."""
    held = [np.column_stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches if b.num_rows]
    if held:
        pairs = np.concatenate(held)
        nodes, root = _roots(pairs[:, 0], pairs[:, 1])
        some = nodes != root
        yield pa.RecordBatch.from_arrays([pa.array(nodes[some]), pa.array(root[some])], names=["u", "v"])


def _with_least(pairs: DataFrame) -> DataFrame:
    """u, v, m: m is the least of u and its neighbours."""
    least = pairs.groupBy("u").agg(F.min("v").alias("w"))
    return pairs.join(least, "u").select("u", "v", F.least("u", "w").alias("m"))


def _by_stars(now: DataFrame, folder: str, name: str) -> DataFrame:
    """u, v: every node that is no root with its root, by rounds of star contractions.

    A round turns larger neighbours to the least of a neighbourhood, then smaller ones; it
    ends when a round changes nothing, after about the logarithm of the longest path. Only
    counts and checksums reach the driver.
    """
    seen, n = None, 0
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        small = _with_least(large)
        down = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        n += 1
        now = written(down.where("u <> v").distinct(), folder, f"{name}{n}")
        forget(now.sparkSession, folder, f"{name}{n - 1}")
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v") % 1_000_000_007)).first()
        if tuple(state) == seen:
            return now
        seen = tuple(state)


def components(edges: DataFrame, folder: str, name: str, in_one: int = IN_ONE) -> DataFrame:
    """node, component (its least node) of every node that has an edge in a, b."""
    pairs = edges.select(F.col("a").cast("long").alias("u"), F.col("b").cast("long").alias("v")).where("u <> v")
    now = written(pairs.mapInArrow(_forest, "u long, v long"), folder, f"{name}0")
    if now.count() <= in_one:
        now = written(now.coalesce(1).mapInArrow(_forest, "u long, v long"), folder, name)
    else:
        now = _by_stars(now.distinct(), folder, name)
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
