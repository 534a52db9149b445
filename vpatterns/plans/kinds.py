"""The workflow for additive, multiplicative and ordered patterns of whole-number cells (obs, var, value).

Variables are grouped by the measure of their coherence, all groups are mined in one job a
level, and the groups' patterns are folded together, one group after another: additive and
multiplicative ones by the difference or ratio of their pivots, ordered ones by how they
interleave. Closed patterns come from closed local ones for the first two; ordered ones
need every frequent local pattern.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators import clustering, similarity
from vpatterns.operators import coherence as H
from vpatterns.operators.prepare import cut, cutoff

KINDS = ("additive", "multiplicative", "order")


def grouped(values: DataFrame, n_obs: int, kind: str, cap: int, strategy: str = "similar", linkage: str = "average") -> DataFrame:
    """var, cluster_id by the similarity that belongs to the kind of coherence."""
    ids = sorted(r["var"] for r in values.select("var").distinct().collect())
    if strategy == "random":
        names = values.sparkSession.createDataFrame([(v, str(v)) for v in ids], "var_id int, item string")
        home = clustering.random_clusters(names, cap)
    else:
        sim = similarity.order_similarity_cells(values, n_obs) if kind == "order" else similarity.difference_similarity(values, n_obs, kind)
        home = clustering.capped_clusters(sim, ids, cap, linkage, strategy)
    return home.select(F.col("var_id").alias("var"), "cluster_id")


def within_groups(values: DataFrame, home: DataFrame) -> DataFrame:
    """The cells with (obs, group) in place of obs: what a miner joins on obs stays inside a group."""
    return values.join(F.broadcast(home), "var").select(F.struct("obs", "cluster_id").alias("obs"), "var", "value")


def discover_kind(values: DataFrame, n_obs: int, min_sup: float, kind: str, cap: int = 4, strategy: str = "similar", linkage: str = "average") -> DataFrame:
    """vars, offsets, support (closed), or seq, support of ordered patterns, of two variables or more."""
    if kind not in KINDS:
        raise ValueError(f"kind must be one of {KINDS}")
    least = cutoff(min_sup, n_obs)
    values = cut(values.select("obs", F.col("var").cast("int").alias("var"), "value"))
    home = cut(grouped(values, n_obs, kind, cap, strategy, linkage))
    groups = [r["cluster_id"] for r in home.select("cluster_id").distinct().orderBy("cluster_id").collect()]
    inside = within_groups(values, home)
    group_of = lambda c: F.element_at(F.col(c), 1)
    if kind == "order":
        single = values.groupBy("var").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least).select(F.array("var").alias("seq"))
        local = cut(H.mine_order(inside, least).select("seq").unionByName(single).join(F.broadcast(home), group_of("seq") == F.col("var")).select("seq", "cluster_id"))
        found = None
        for g in groups:
            mine = local.where(F.col("cluster_id") == g).select("seq")
            if found is not None:
                both = cut(H.merge_order(found, mine, values, least))
                mine = mine.unionByName(both.select("seq"))
            found = cut(mine if found is None else found.unionByName(mine))
        return H.order_support(values, (local.select("seq") if found is None else found).where("size(seq) > 1"), least)
    mined = cut(H.mine_offsets(inside, least, kind))
    local = H.closed_offsets(mined, kind)
    rows = cut(H.offset_rows(values, local, kind).join(F.broadcast(home), group_of("vars") == F.col("var")).drop("var"))
    found = None
    for g in groups:
        mine = rows.where(F.col("cluster_id") == g).drop("cluster_id")
        if found is not None:
            mine = mine.unionByName(H.merge_offset(found, mine, least, kind))
        found = cut(mine if found is None else found.unionByName(mine))
    found = rows.drop("cluster_id") if found is None else found
    counted = found.where("size(vars) > 1").groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
    # the pivot is the least variable, whichever group it came from
    return H.closed_offsets(cut(H.from_least(counted, kind)), kind)
