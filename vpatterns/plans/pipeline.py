"""The whole workflow: group variables, mine every group, recombine to closed patterns."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators import clustering as C
from vpatterns.operators import merge as M
from vpatterns.operators import mining, prepare, similarity
from vpatterns.sources.workloads import Matrix

STRATEGIES = ("similar", "dissimilar", "random")


@dataclass
class Discovery:
    """Result of one run: closed patterns (mask, support), groups, local patterns, measures."""

    patterns: DataFrame
    assignment: DataFrame
    local: DataFrame
    measures: dict = field(default_factory=dict)


def group_variables(sig: DataFrame, variables: DataFrame, n_obs: int, cap: int, strategy: str, linkage: str = "average", score: str = "sim", missing: str = "skip") -> DataFrame:
    """var_id, cluster_id by one of the three strategies."""
    if strategy == "random":
        return C.random_clusters(variables, cap)
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy must be one of {STRATEGIES}")
    joint, single = similarity.joint_counts_of_signatures(sig), similarity.marginals_of_signatures(sig)
    sim = similarity.jaccard(joint, single) if score == "score" else similarity.pattern_similarity(joint, single, n_obs, missing)
    ids = sorted(r["var_id"] for r in variables.select("var_id").collect())  # at most a mask's places
    grid = sig.sparkSession.createDataFrame([(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :]], "a int, b int")
    full = grid.join(F.broadcast(sim), ["a", "b"], "left").select("a", "b", F.coalesce(score, F.lit(0.0)).alias("s"))
    return C.capped_clusters(full, ids, cap, linkage, "similar" if strategy == "similar" else "dissimilar", "s")


def local_patterns(sig: DataFrame, assignment: DataFrame, least: int, closed: bool = True) -> DataFrame:
    """cluster_id, mask (over all variables), support of every group, mined in one job a level."""
    groups = assignment.groupBy("cluster_id").agg(F.bit_or(prepare.bit_of("var_id")).alias("own"))  # at most a mask's places
    parts = sig.join(F.broadcast(groups)).select("cluster_id", F.expr("mask & own").alias("mask"), "w").where("mask <> 0")
    parts = parts.groupBy("cluster_id", "mask").agg(F.sum("w").alias("w"))
    found = mining.apriori(parts, least, keys=("cluster_id",))
    if not closed:
        return found
    hit = mining.containing(found.select("cluster_id", "mask"), parts, ("cluster_id",), found.count())
    ids = hit.groupBy("_cluster_id", "_mask").agg(F.sum("w").alias("support"), F.bit_xor(F.xxhash64("mask")).alias("h1"), F.bit_xor(F.xxhash64("mask", F.lit(1))).alias("h2"))
    shut = ids.groupBy(F.col("_cluster_id").alias("cluster_id"), "support", "h1", "h2").agg(F.bit_or("_mask").alias("mask"))
    return shut.select("cluster_id", "mask", "support")


def discover(matrix: Matrix, variables: DataFrame, min_sup: float, cap: int = 4, strategy: str = "similar", merge: str = "sequential", linkage: str = "average", closed_local: bool = True, score: str = "sim") -> Discovery:
    """Closed frequent patterns of constant coherence over the chosen variables.

    More than a mask holds (62) is an error; ``plans.find`` takes any number.
    """
    began = time.perf_counter()
    least = prepare.cutoff(min_sup, matrix.n_obs)
    sig = prepare.cut(prepare.signatures(matrix.cells, variables))
    assignment = group_variables(sig, variables, matrix.n_obs, cap, strategy, linkage, score)
    local = prepare.cut(local_patterns(sig, assignment, least, closed_local))
    ids = [r["cluster_id"] for r in local.select("cluster_id").distinct().orderBy("cluster_id").collect()]
    parts = [local.where(F.col("cluster_id") == c).select("mask", "support") for c in ids]
    mined = time.perf_counter()
    work = {}
    if not parts:
        patterns = local.select("mask", "support")
    elif merge == "tree":
        patterns = M.merge_tree(parts, sig, least)
    elif merge == "membership":
        patterns = M.merge_membership(parts, sig, least)
    else:
        patterns, work = M.merge_sequential(parts, sig, least)
    patterns = prepare.cut(patterns)
    ended = time.perf_counter()
    return Discovery(patterns, assignment, local, {"whole_s": ended - began, "merge_s": ended - mined, **work})


def discover_global(matrix: Matrix, variables: DataFrame, min_sup: float) -> DataFrame:
    """The same patterns without any grouping."""
    sig = prepare.cut(prepare.signatures(matrix.cells, variables))
    return M.closed_collapse(mining.apriori(sig, prepare.cutoff(min_sup, matrix.n_obs)), sig)


def contract(patterns: DataFrame) -> DataFrame:
    """pattern, n_vars, support as queries return them."""
    return patterns.select(prepare.as_text("mask").alias("pattern"), F.bit_count("mask").alias("n_vars"), F.col("support").cast("long").alias("support"))
