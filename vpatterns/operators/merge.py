"""Closed patterns, and recombination of patterns of disjoint groups of variables.

Masks are over all chosen variables here, so a combined pattern is the OR of its parts and
its support is counted over the joint signatures.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators.mining import BROADCAST_CANDIDATES, containing, support
from vpatterns.operators.prepare import bits, cut


def closed_pairwise(patterns: DataFrame) -> DataFrame:
    """Patterns without a strict superset of the same support (thus of the same rows)."""
    other = patterns.select(F.col("mask").alias("m2"), F.col("support").alias("s2"))
    return patterns.join(other, F.expr("support = s2 and mask <> m2 and (mask & m2) = mask"), "left_anti")


def with_cover(patterns: DataFrame, sig: DataFrame) -> DataFrame:
    """mask, support and a 128-bit number of the set of signatures that hold each mask."""
    asked = cut(patterns.select("mask").distinct())
    ids = containing(asked, sig, n=asked.count()).groupBy(F.col("_mask").alias("p")).agg(F.sum("w").alias("support"), F.bit_xor(F.xxhash64("mask")).alias("h1"), F.bit_xor(F.xxhash64("mask", F.lit(1))).alias("h2"))
    return ids.withColumnRenamed("p", "mask")


def closed_collapse(patterns: DataFrame, sig: DataFrame) -> DataFrame:
    """The same by grouping on the set of rows: the union of variables is the closed pattern.

    Grows with the number of patterns, not its square. For constant coherence only.
    """
    return with_cover(patterns, sig).groupBy("support", "h1", "h2").agg(F.bit_or("mask").alias("mask")).select("mask", "support")


def maximal(patterns: DataFrame) -> DataFrame:
    """Patterns without any strict superset among them; supersets are met on the lowest variable."""
    above = containing(patterns.select("mask"), patterns.select("mask"))
    return patterns.join(above.where("mask <> _mask").select(F.col("_mask").alias("mask")).distinct(), "mask", "left_anti")


def combined(current: DataFrame, more: DataFrame, sig: DataFrame, least: int, n_pairs: int) -> DataFrame:
    """All patterns of ``current`` with one of ``more`` whose common rows reach the threshold.

    ``n_pairs`` is their counted product. Few pairs are made and counted as masks; many are
    never made: only patterns that some row holds together meet, by a join on the row.
    """
    if n_pairs <= BROADCAST_CANDIDATES:
        pairs = current.select(F.col("mask").alias("m1")).crossJoin(F.broadcast(more.select(F.col("mask").alias("m2"))))
        made = pairs.select(F.expr("m1 | m2").alias("mask")).distinct()
        return support(made, sig, n=n_pairs).where(F.col("support") >= least)
    held = lambda p, name: containing(p.select("mask"), sig).select(F.col("mask").alias("row"), "w", F.col("_mask").alias(name))
    met = held(current, "m1").join(held(more, "m2").drop("w"), "row")
    return met.groupBy(F.expr("m1 | m2").alias("mask")).agg(F.sum("w").alias("support")).where(F.col("support") >= least)


def merge_sequential(local: list[DataFrame], sig: DataFrame, least: int) -> tuple[DataFrame, dict]:
    """(closed patterns, work counters): from each group, sweep the later ones.

    A sweep combines what was there before it began. What a group starts is reduced to
    patterns that nothing else encloses, earlier final ones included.
    """
    work = {"compared": 0, "kept": 0}
    final = None
    sizes = [x.count() for x in local]
    for i, start in enumerate(local):
        current, n = start.select("mask", "support"), sizes[i]
        for j in range(i + 1, len(local)):
            made = cut(combined(current, local[j], sig, least, n * sizes[j]))
            work["compared"] += n * sizes[j]
            fresh = made.count()
            work["kept"] += fresh
            current, n = current.unionByName(made), n + fresh
        shut = closed_collapse(current, sig)
        if final is not None:
            ids = final.select(F.col("mask").alias("m2"), F.col("support").alias("s2"))
            shut = shut.join(ids, F.expr("support = s2 and (mask & m2) = mask"), "left_anti")
            final = cut(final.unionByName(shut))
        else:
            final = cut(shut)
    return final, work


def merge_tree(local: list[DataFrame], sig: DataFrame, least: int) -> DataFrame:
    """The same by merging neighbours, closed after each round: log2 rounds."""
    level = [(x.select("mask", "support"), x.count()) for x in local]
    while len(level) > 1:
        nxt = []
        for (x, n), (y, m) in zip(level[::2], level[1::2]):
            both = cut(closed_collapse(x.unionByName(y).unionByName(combined(x, y, sig, least, n * m)), sig))
            nxt.append((both, both.count()))
        level = nxt + level[len(level) & ~1 :]
    return closed_collapse(level[0][0], sig)


def merge_membership(local: list[DataFrame], sig: DataFrame, least: int) -> DataFrame:
    """The same through membership: rows that hold a combined pattern meet the next group's.

    Rows are signature ids with the patterns they hold, so neither masks over all
    variables nor row lists are needed; each group is one join on the row.
    """
    member = [containing(p.select("mask"), sig, n=p.count()).select(F.col("mask").alias("row"), "w", F.col("_mask").alias("p")) for p in local]
    now = None
    for m in member:
        if now is None:
            now = m.select("row", "w", F.col("p").alias("c"))
            continue
        both = now.join(m.select("row", "p"), "row").select("row", "w", F.expr("c | p").alias("c"))
        kept = both.groupBy("c").agg(F.sum("w").alias("s")).where(F.col("s") >= least).select("c")
        now = cut(now.unionByName(m.select("row", "w", F.col("p").alias("c"))).unionByName(both.join(kept, "c", "left_semi")))
    ids = now.groupBy("c").agg(F.sum("w").alias("support"), F.bit_xor(F.xxhash64("row")).alias("h1"), F.bit_xor(F.xxhash64("row", F.lit(1))).alias("h2"))
    return ids.groupBy("support", "h1", "h2").agg(F.bit_or("c").alias("mask")).select("mask", "support")


def verify_complete(merged: DataFrame, globally: DataFrame) -> DataFrame:
    """missing, extra: patterns on one side only."""
    a, b = merged.select("mask", "support"), globally.select("mask", "support")
    return b.exceptAll(a).agg(F.count(F.lit(1)).alias("missing")).crossJoin(a.exceptAll(b).agg(F.count(F.lit(1)).alias("extra")))


def drop_overlapping(patterns: DataFrame, sig: DataFrame, theta: float) -> DataFrame:
    """Patterns that share at most theta of their area with a better one (more area, then lower mask).

    Area is variables times rows; the overlap of two is their common variables times the
    rows that hold both, over the union of the areas.
    """
    p = patterns.select("mask", "support", F.expr("bit_count(mask) * support").alias("area"))
    q = p.select(F.col("mask").alias("m2"), F.col("support").alias("s2"), F.col("area").alias("a2"))
    # two patterns meet once, on the lowest variable that they share
    one = p.withColumn("v", F.explode(bits("mask"))).join(q.withColumn("v", F.explode(bits("m2"))), "v")
    pair = one.where("shiftleft(1L, v) = ((mask & m2) & -(mask & m2)) and (a2 > area or (a2 = area and m2 < mask))").drop("v")
    both = support(pair.select(F.expr("mask | m2").alias("mask")).distinct(), sig).select(F.col("mask").alias("u"), F.col("support").alias("common"))
    scored = pair.withColumn("u", F.expr("mask | m2")).join(both, "u", "left")
    shared = F.coalesce("common", F.lit(0)) * F.expr("bit_count(mask & m2)")
    bad = scored.where(shared / (F.col("area") + F.col("a2") - shared) > theta).select("mask").distinct()
    return p.join(bad, "mask", "left_anti").select("mask", "support")


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
