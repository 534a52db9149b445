"""The workflow for any number of variables: masks stay inside groups, nothing is 2**M.

A row is the list of its groups' masks; equal rows are one row with a weight. Local closed
patterns of all groups are mined in one job a level. They are the items of the merge: a
combined pattern grows by a pattern of a later group over the rows that hold both, so the
number of jobs is the largest number of groups that a pattern spans, not that of groups.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.operators import clustering, mining, prepare, similarity
from vpatterns.operators.prepare import cut
from vpatterns.sources.workloads import Matrix


def placed_variables(matrix: Matrix, variables: DataFrame, cap: int, strategy: str, linkage: str = "average") -> DataFrame:
    """item, cluster_id, bit of every variable."""
    if strategy == "random":
        home = clustering.random_clusters(variables, cap)
    else:
        cells = matrix.cells.join(variables, "item").select("obs", "var_id", F.lit(1).alias("level"), prepare.weight(matrix.cells).alias("w"))
        sim = similarity.pattern_similarity(similarity.joint_counts(cells), similarity.marginals(cells), matrix.n_obs)
        n = variables.count()
        if n <= clustering.DRIVER_LIMIT:
            home = clustering.capped_clusters(sim, list(range(n)), cap, linkage, strategy)
        else:
            home = clustering.capped_clusters_df(sim, variables.select(F.col("var_id").cast("int").alias("var_id")), cap, strategy, linkage=linkage)
    bit = F.row_number().over(W.partitionBy("cluster_id").orderBy("var_id")) - 1
    return variables.join(home, "var_id").select("item", "cluster_id", bit.alias("bit"))


def weighted_rows(matrix: Matrix, placed: DataFrame) -> DataFrame:
    """row, w, cluster_id, mask: distinct rows as their groups' masks, one line a group."""
    masks = matrix.cells.join(placed, "item").groupBy("obs", "cluster_id").agg(F.bit_or(prepare.bit_of("bit")).alias("mask"), F.first(prepare.weight(matrix.cells)).alias("w"))
    rows = masks.groupBy("obs").agg(F.array_sort(F.collect_list(F.struct("cluster_id", "mask"))).alias("parts"), F.first("w").alias("w")).groupBy("parts").agg(F.sum("w").alias("w"))
    numbered = cut(rows.withColumn("row", F.monotonically_increasing_id()))
    return numbered.select("row", "w", F.explode("parts").alias("p")).select("row", "w", "p.cluster_id", "p.mask")


def closed_local(rows: DataFrame, least: int) -> DataFrame:
    """cluster_id, p, support: closed frequent patterns of every group."""
    sig = cut(rows.groupBy("cluster_id", "mask").agg(F.sum("w").alias("w")))
    found = mining.mine_partitions(sig, least).select(F.col("cluster_id"), F.col("mask").alias("p"))
    hit = sig.join(found, "cluster_id").where("(mask & p) = p")
    ids = hit.groupBy("cluster_id", "p").agg(F.sum("w").alias("s"), F.bit_xor(F.xxhash64("mask")).alias("h1"), F.bit_xor(F.xxhash64("mask", F.lit(1))).alias("h2"))
    return ids.groupBy("cluster_id", "s", "h1", "h2").agg(F.bit_or("p").alias("p")).select("cluster_id", "p", F.col("s").alias("support"))


def merged(rows: DataFrame, local: DataFrame, least: int) -> DataFrame:
    """parts (cluster_id, p of each group touched), support of all closed patterns."""
    member = cut(rows.join(local, "cluster_id").where("(mask & p) = p").select("row", "w", "cluster_id", "p"))
    held = member.select("row", "w", F.array(F.struct("cluster_id", "p")).alias("c"), F.col("cluster_id").alias("last"))
    levels = [held]
    while True:
        more = member.select("row", F.struct("cluster_id", "p").alias("item"), F.col("cluster_id").alias("next"))
        longer = held.join(more, "row").where("next > last").select("row", "w", F.array_append("c", F.col("item")).alias("c"), F.col("next").alias("last"))
        kept = longer.groupBy("c").agg(F.sum("w").alias("s")).where(F.col("s") >= least).select("c")
        held = cut(longer.join(kept, "c", "left_semi"))
        if not held.limit(1).count():
            break
        levels.append(held)
    ids = None
    for x in levels:
        one = x.groupBy("c").agg(F.sum("w").alias("support"), F.bit_xor(F.xxhash64("row")).alias("h1"), F.bit_xor(F.xxhash64("row", F.lit(1))).alias("h2"))
        ids = one if ids is None else ids.unionByName(one)
    each = ids.where(F.col("support") >= least).select("support", "h1", "h2", F.explode("c").alias("e"))
    union = each.groupBy("support", "h1", "h2", "e.cluster_id").agg(F.bit_or("e.p").alias("p"))
    return union.groupBy("support", "h1", "h2").agg(F.array_sort(F.collect_list(F.struct("cluster_id", "p"))).alias("parts")).select("parts", "support")


def discover_wide(matrix: Matrix, min_sup: float, cap: int = 8, strategy: str = "similar", variables: DataFrame | None = None, linkage: str = "average") -> DataFrame:
    """items (sorted), support of all closed frequent patterns of constant coherence."""
    least = prepare.cutoff(min_sup, matrix.n_obs)
    variables = prepare.numbered(matrix.cells.select("item").distinct()) if variables is None else variables
    placed = cut(placed_variables(matrix, cut(variables), cap, strategy, linkage))
    rows = cut(weighted_rows(matrix, placed))
    found = merged(rows, cut(closed_local(rows, least)), least)
    one = found.select("parts", "support", F.explode("parts").alias("e"))
    named = one.join(placed, F.expr("e.cluster_id = cluster_id and getbit(e.p, bit) = 1"))
    return named.groupBy("parts", "support").agg(F.array_sort(F.collect_list("item")).alias("items")).select("items", "support")
