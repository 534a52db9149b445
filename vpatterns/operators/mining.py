"""Miners of one table of weighted signatures, or of all partitions of it at once."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vpatterns.operators.prepare import MASK_BITS, cut, cutoff

#: Candidates that are sent to all tasks at most; more are met by an equi-join on their lowest variable.
BROADCAST_CANDIDATES = 200_000


def _lowest(mask: str):
    return F.expr(f"{mask} & -{mask}")


def containing(candidates: DataFrame, sig: DataFrame, keys: tuple[str, ...] = (), n: int | None = None) -> DataFrame:
    """Signatures (mask, w) beside each mask (_mask, with _keys) that they hold.

    ``n`` is the counted number of candidates: up to BROADCAST_CANDIDATES they are sent to
    all tasks; more, or an unknown number, meet the signatures on their lowest variable.
    """
    c = candidates.select(*[F.col(k).alias(f"_{k}") for k in keys], F.col("mask").alias("_mask"))
    hit = F.expr("(mask & _mask) = _mask")
    for k in keys:
        hit = hit & (F.col(k) == F.col(f"_{k}"))
    if n is not None and n <= BROADCAST_CANDIDATES:
        return sig.join(F.broadcast(c), hit)
    places = F.filter(F.sequence(F.lit(0), F.lit(MASK_BITS - 1)), lambda i: F.getbit("mask", i) == 1)
    # a row of no variable holds no candidate
    spread = sig.withColumn("_low", F.explode(F.transform(places, lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i))))
    return spread.join(c.withColumn("_low", _lowest("_mask")), "_low").where(hit)


def support(candidates: DataFrame, sig: DataFrame, keys: tuple[str, ...] = (), n: int | None = None) -> DataFrame:
    """keys, mask, support: summed weights of the signatures that hold each mask."""
    met = containing(candidates, sig, keys, n)
    return met.groupBy(*[f"_{k}" for k in keys], "_mask").agg(F.sum("w").alias("support")).select(*[F.col(f"_{k}").alias(k) for k in keys], F.col("_mask").alias("mask"), "support")


def apriori(sig: DataFrame, least, keys: tuple[str, ...] = (), max_len: int | None = None) -> DataFrame:
    """keys, mask, support of all masks whose weight is ``least`` (a number, or an expression over the keys) or more.

    Level by level: two frequent sets that differ in their highest variable make a
    candidate, candidates with an infrequent subset go, the rest are counted over the
    signatures. With ``keys`` all partitions advance together, one job a level.
    """
    sig = sig.persist()
    places = F.filter(F.sequence(F.lit(0), F.lit(MASK_BITS - 1)), lambda i: F.getbit("mask", i) == 1)
    one = sig.select(*keys, "w", F.explode(places).alias("i")).groupBy(*keys, "i").agg(F.sum("w").alias("support")).where(F.col("support") >= least)
    level = cut(one.select(*keys, F.expr("shiftleft(1L, i)").alias("mask"), F.col("i").alias("last"), "support"))
    found, size = [level], 1
    while level.limit(1).count() and (max_len is None or size < max_len):
        rest = F.expr("mask ^ shiftleft(1L, last)")
        x = level.select(*keys, rest.alias("p"), F.col("last").alias("l1"), F.col("mask").alias("m1"))
        y = level.select(*keys, rest.alias("p"), F.col("last").alias("last"), F.col("mask").alias("m2"))
        joined = x.join(y, [*keys, "p"]).where("l1 < last").select(*keys, F.expr("m1 | m2").alias("mask"), "last")
        if size > 1:
            sub = joined.select(*keys, "mask", "last", F.explode(F.transform(places, lambda i: F.expr("mask").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i)))).alias("sub"))
            known = level.select(*keys, F.col("mask").alias("sub"))
            whole = sub.join(known, [*keys, "sub"], "left_semi").groupBy(*keys, "mask", "last").agg(F.count(F.lit(1)).alias("n"))
            joined = whole.where(F.col("n") == size + 1).select(*keys, "mask", "last")
        candidates = cut(joined)
        n = candidates.count()
        if not n:
            break
        counted = support(candidates, sig, keys, n).where(F.col("support") >= least)
        level = cut(counted.join(candidates, [*keys, "mask"]).select(*keys, "mask", "last", "support"))
        size += 1
        found.append(level)
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    sig.unpersist()
    return out.select(*keys, "mask", "support")


def enumerate_patterns(sig: DataFrame, n_vars: int, least: int) -> DataFrame:
    """The same by trying all masks; for clusters of 16 variables at most."""
    if n_vars > 16:
        raise ValueError("enumeration is for 16 variables at most")
    masks = sig.sparkSession.range(1, 1 << n_vars).select(F.col("id").alias("p"))
    met = masks.join(F.broadcast(sig), F.expr("(mask & p) = p"))
    return met.groupBy("p").agg(F.sum("w").alias("support")).where(F.col("support") >= least).select(F.col("p").alias("mask"), "support")


def mine_partitions(sig_of_clusters: DataFrame, least: int) -> DataFrame:
    """cluster_id, mask (places inside the cluster), support of all partitions."""
    return apriori(sig_of_clusters, least, keys=("cluster_id",))


def frequent_items(cells: DataFrame, least: int) -> DataFrame:
    return cells.groupBy("item").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)


def fpgrowth(cells: DataFrame, n_obs: int, min_sup: float) -> DataFrame:
    """items, freq by the library's miner; its threshold is inclusive, so it gets the strict cut."""
    from pyspark.ml.fpm import FPGrowth

    rows = cells.groupBy("obs").agg(F.collect_set("item").alias("items"))
    rows = rows.persist()
    n = rows.count()
    out = FPGrowth(itemsCol="items", minSupport=max(0.0, (cutoff(min_sup, n_obs) - 0.5) / max(1, n))).fit(rows).freqItemsets
    return out.where(F.col("freq") >= cutoff(min_sup, n_obs))


def mine_horizontal(sig: DataFrame, parts: int, n_obs: int, min_sup: float) -> DataFrame:
    """Related work: large sets of horizontal parts, then one recount over all rows.

    Signatures are dealt out with their weights; a set that is frequent overall is
    frequent in one part at least, so the union of local results holds all.
    """
    dealt = sig.withColumn("part", F.pmod(F.xxhash64("mask"), F.lit(parts)).cast("int"))
    size = {r["part"]: r["n"] for r in dealt.groupBy("part").agg(F.sum("w").alias("n")).collect()}
    held = max(1, sum(size.values()))
    # rows without any variable belong to no part; the rest share the threshold
    least = F.create_map(*[F.lit(x) for p, n in size.items() for x in (p, max(1, -(-cutoff(min_sup, n_obs) * n // held)))])[F.col("part")] if size else 1
    found = cut(apriori(dealt, least, keys=("part",)).select("mask").distinct())
    return support(found, sig, n=found.count()).where(F.col("support") >= cutoff(min_sup, n_obs))


def mine_by_prefix(sig: DataFrame, least: int) -> DataFrame:
    """Related work: the search space dealt out by first variable; each part mines its own rows."""
    places = F.filter(F.sequence(F.lit(0), F.lit(MASK_BITS - 1)), lambda i: F.getbit("mask", i) == 1)
    rows = sig.select("w", "mask", F.explode(places).alias("prefix"))
    own = rows.select("prefix", F.expr("mask & ~(shiftleft(1L, prefix) - 1)").alias("mask"), "w").groupBy("prefix", "mask").agg(F.sum("w").alias("w"))
    found = apriori(own, least, keys=("prefix",))
    return found.where("(mask & shiftleft(1L, prefix)) <> 0").select("mask", "support")


def sample_mine(sig: DataFrame, fraction: float, n_obs: int, min_sup: float) -> DataFrame:
    """Related work, approximate: sets frequent in a sample of signatures, recounted over all.

    The sample's threshold is a fifth lower, so few sets are missed; no set is returned
    that is not frequent, and supports are exact. ``recall`` measures what is found.
    """
    part = sig.where(F.pmod(F.xxhash64("mask"), F.lit(1000)) < int(1000 * fraction))
    least = max(1, int(cutoff(min_sup, n_obs) * fraction * 0.8))
    return support(apriori(part, least).select("mask"), sig).where(F.col("support") >= cutoff(min_sup, n_obs))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """found, exact, recall: how many of the exact patterns an approximate search gives."""
    kept = exact.select("mask", "support").join(found.select("mask", "support"), ["mask", "support"], "left_semi")
    both = exact.agg(F.count(F.lit(1)).alias("exact")).crossJoin(kept.agg(F.count(F.lit(1)).alias("found")))
    return both.select("found", "exact", (F.col("found") / F.nullif("exact", F.lit(0))).alias("recall"))
