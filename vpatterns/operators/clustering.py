"""Disjoint groups of variables, none above a cap."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.operators.prepare import cut

#: Variables whose pairs the driver may hold; it never sees observations.
DRIVER_LIMIT = 5000
LINKAGES = ("average", "single", "complete")


def fuse_matrix(s: np.ndarray, cap: int, linkage: str = "average", direction: str = "similar"):
    """(least member of each variable's cluster, log of fusions) from a symmetric matrix; nan is no pair.

    Every row keeps its best later partner. A fusion changes one row, and only rows whose
    partner was one of the two are searched again, so thousands of variables take seconds.
    The matrix is overwritten.
    """
    if linkage not in LINKAGES:
        raise ValueError(f"linkage must be one of {LINKAGES}")
    n, sign = len(s), 1.0 if direction == "similar" else -1.0
    size, alive, home, log = np.ones(n, np.int64), np.ones(n, bool), np.arange(n), []
    best, mate = np.full(n, -np.inf), np.full(n, -1)

    def value(i, js):
        v = sign * np.round(s[i, js], 9)
        return np.where(alive[js] & (size[js] + size[i] <= cap) & ~np.isnan(v), v, -np.inf)

    def search(i):
        v = value(i, slice(i + 1, n))
        k = int(v.argmax()) if len(v) else 0
        best[i], mate[i] = (v[k], i + 1 + k) if len(v) and v[k] > -np.inf else (-np.inf, -1)

    for i in range(n):
        search(i)
    while n and best.max() > -np.inf:
        x = int(best.argmax())  # the first of equal ones has the least ids
        y = int(mate[x])
        log.append((len(log), x, y, float(np.round(s[x, y], 9))))
        sx, sy = s[x], s[y]
        if linkage == "average":
            new = (size[x] * np.nan_to_num(sx) + size[y] * np.nan_to_num(sy)) / (size[x] + size[y])
        else:
            new = (np.fmax if linkage == "single" else np.fmin)(sx, sy)
        new = np.where((np.isnan(sx) & np.isnan(sy)) | ~alive, np.nan, new)
        new[[x, y]] = np.nan
        s[x], s[:, x] = new, new
        s[y], s[:, y] = np.nan, np.nan
        alive[y], best[y], mate[y] = False, -np.inf, -1
        size[x] += size[y]
        home[home == y] = x
        again = alive & ((mate == x) | (mate == y))
        again[x] = True
        for i in np.flatnonzero(again):
            search(int(i))
        before = np.flatnonzero(alive[:x] & ~again[:x])
        v = sign * np.round(s[before, x], 9)
        v = np.where((size[before] + size[x] <= cap) & ~np.isnan(v), v, -np.inf)
        gain = (v > best[before]) | ((v == best[before]) & (v > -np.inf) & (x < mate[before]))
        best[before[gain]], mate[before[gain]] = v[gain], x
    return home, log


def fuse(scores: dict[tuple[int, int], float], variables: list[int], cap: int, linkage: str = "average", direction: str = "similar"):
    """(assignment, log of fusions) by fusing the best pair whose total is within the cap.

    Ties go to the least ids. A cluster that no other fits beside leaves the race. Pairs
    without a score are not fused on their own; on average they count as 0.
    """
    ids = sorted(variables)
    at = {v: i for i, v in enumerate(ids)}
    s = np.full((len(ids), len(ids)), np.nan)
    for (a, b), x in scores.items():
        s[at[a], at[b]] = s[at[b], at[a]] = x
    home, log = fuse_matrix(s, cap, linkage, direction)
    return {v: ids[home[i]] for i, v in enumerate(ids)}, [(k, ids[x], ids[y], c) for k, x, y, c in log]


def capped_clusters(sim: DataFrame, variables: list[int], cap: int, linkage: str = "average", direction: str = "similar", score: str = "sim") -> DataFrame:
    """var_id, cluster_id (least member): pairs of at most DRIVER_LIMIT variables are fused on the driver."""
    if len(variables) > DRIVER_LIMIT:
        return capped_clusters_df(sim, sim.sparkSession.createDataFrame([(v,) for v in variables], "var_id int"), cap, direction, score, linkage)
    ids = np.array(sorted(variables), np.int64)
    pairs = sim.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"), F.col(score).cast("double").alias("s")).where("s is not null").toArrow()
    a, b = (np.searchsorted(ids, pairs.column(c).to_numpy()) for c in ("a", "b"))
    s = np.full((len(ids), len(ids)), np.nan)
    s[a, b] = s[b, a] = pairs.column("s").to_numpy()
    home, _ = fuse_matrix(s, cap, linkage, direction)
    return sim.sparkSession.createDataFrame([(int(v), int(ids[h])) for v, h in zip(ids, home)], "var_id int, cluster_id int")


def capped_clusters_df(sim: DataFrame, variables: DataFrame, cap: int, direction: str = "similar", score: str = "sim", linkage: str = "average") -> DataFrame:
    """The same for any number of variables: each round fuses all pairs that are each other's best.

    A round may fuse what the one-by-one order would not, so clusters may differ from
    ``capped_clusters``; patterns found with them are the same.
    """
    if linkage not in LINKAGES:
        raise ValueError(f"linkage must be one of {LINKAGES}")
    link = {"average": F.avg, "single": F.max, "complete": F.min}[linkage]
    home = variables.select("var_id", F.col("var_id").alias("cluster_id"), F.lit(1).alias("size"))
    base = sim.select("a", "b", F.round(score, 9).alias("s"))
    while True:
        x, y = home.select(F.col("var_id").alias("a"), F.col("cluster_id").alias("ca"), F.col("size").alias("na")), home.select(F.col("var_id").alias("b"), F.col("cluster_id").alias("cb"), F.col("size").alias("nb"))
        pairs = base.join(x, "a").join(y, "b").where(f"ca <> cb and na + nb <= {cap}")
        pairs = pairs.groupBy(F.least("ca", "cb").alias("u"), F.greatest("ca", "cb").alias("v")).agg(link("s").alias("s"))
        both = pairs.select("u", "v", "s").unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"), "s"))
        order = F.desc("s") if direction == "similar" else F.asc("s")
        best = both.withColumn("r", F.row_number().over(W.partitionBy("u").orderBy(order, "v"))).where("r = 1").select("u", "v")
        back = best.select(F.col("v").alias("u"), F.col("u").alias("v"))
        fused = cut(best.join(back, ["u", "v"]).where("u < v"))
        if not fused.limit(1).count():
            return home.select("var_id", "cluster_id")
        home = home.join(fused, home.cluster_id == fused.v, "left").select("var_id", F.coalesce("u", "cluster_id").alias("cluster_id"))
        home = cut(home.withColumn("size", F.count(F.lit(1)).over(W.partitionBy("cluster_id")).cast("int")))


def random_clusters(variables: DataFrame, cap: int, seed: int = 42, name: str = "item") -> DataFrame:
    """var_id, cluster_id: groups of cap variables in the order of a digest of their names."""
    rank = F.row_number().over(W.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(name))), name)) - 1
    grouped = variables.select("var_id", F.floor(rank / cap).alias("g"))
    return grouped.select(F.col("var_id").cast("int").alias("var_id"), F.min("var_id").over(W.partitionBy("g")).cast("int").alias("cluster_id"))


def overlapping_clusters(sim: DataFrame, cap: int, score: str = "sim") -> DataFrame:
    """cluster_id, var_id: each variable with its cap - 1 nearest; groups may overlap (related work)."""
    both = sim.select("a", "b", score).unionByName(sim.select(F.col("b").alias("a"), F.col("a").alias("b"), score))
    near = both.withColumn("r", F.row_number().over(W.partitionBy("a").orderBy(F.desc(score), "b"))).where(f"r < {cap}")
    own = both.select(F.col("a").alias("cluster_id"), F.col("a").alias("var_id")).distinct()
    return near.select(F.col("a").alias("cluster_id"), F.col("b").alias("var_id")).unionByName(own)


def cluster_quality(sim: DataFrame, assignment: DataFrame, score: str = "sim") -> DataFrame:
    """cluster_id, n_vars, mean similarity inside and to the others."""
    x, y = assignment.select(F.col("var_id").alias("a"), F.col("cluster_id").alias("ca")), assignment.select(F.col("var_id").alias("b"), F.col("cluster_id").alias("cb"))
    rows = sim.join(F.broadcast(x), "a").join(F.broadcast(y), "b")
    ends = rows.select(F.explode(F.array_distinct(F.array("ca", "cb"))).alias("cluster_id"), (F.col("ca") == F.col("cb")).alias("inside"), score)
    mean = ends.groupBy("cluster_id").agg(F.avg(F.when(F.col("inside"), F.col(score))).alias("intra"), F.avg(F.when(~F.col("inside"), F.col(score))).alias("inter"))
    return assignment.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_vars")).join(mean, "cluster_id", "left")
