"""Mixing sources to target weights by weighted fair queueing, with DataFrame functions only.

Each source is shuffled by a digest of its ids. A document's entry in a round gets a
virtual finish time: the words of its source up to and including it, over the source's
target. All entries are put in order of finish time and cut where the total budget is
reached. Running sums are taken in two levels (sums of ranges, then sums inside a
range), so neither a hot source nor the global order ever meets in one task.

Defined cases: null texts and texts without words have size 0 and are taken as 0 words;
a null source is a source of its own, after all others; repeated rows are separate
documents; a corpus without words takes nothing; other columns pass through ``mixed``
and are not read by ``plan``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.llm.common import WORD, documents, input_bytes, scratch, written

#: Sources by code point weigh so much, repeating.
WEIGHTS = (5, 2, 1)
#: Percent of all words that the mix has, and the most rounds over a source.
SHARE, ROUNDS = 150, 2
#: Ranges of a source's shuffle and of finish times, at least; each holds a small part of the rows.
RANGES = 1024
#: Bytes of input for each range where that makes more of them.
RANGE_BYTES = 256 << 20


def words(text: str = "text"):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, share: int = SHARE, rounds: int = ROUNDS) -> DataFrame:
    """source, source_size, target from source, source_size: one row a source.

    Sources stop at ``rounds`` times their size; what is left over is shared by weight
    until none is above. Sorted by stop over weight, the sources that stop are a prefix,
    so the level of the others follows from sums over that order.
    """
    by_name = W.orderBy(F.col("source").asc_nulls_last())
    pick = F.array(*[F.lit(float(w)) for w in weights])
    s = sizes.withColumn("weight", F.element_at(pick, ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("stop", F.col("source_size") * float(rounds)).withColumn("ratio", F.col("stop") / F.col("weight"))
    order = W.orderBy("ratio", F.col("source").asc_nulls_last())
    before, after = order.rowsBetween(W.unboundedPreceding, -1), order.rowsBetween(0, W.unboundedFollowing)
    everything = W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    budget = F.sum("source_size").over(everything) * float(share) / 100.0
    s = s.withColumn("level", (budget - F.coalesce(F.sum("stop").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    s = s.withColumn("level", F.max("level").over(everything))  # it rises up to the first source that does not stop
    return s.select("source", "source_size", F.coalesce(F.least("stop", F.col("weight") * F.col("level")), F.col("stop")).alias("target"))


def plan(df: DataFrame, id_col: str = "doc_id", weights=WEIGHTS, share: int = SHARE, rounds: int = ROUNDS, ranges: int | None = None, size=None) -> DataFrame:
    """id, size, source_size, target, copies and taken of every row of df.

    ``ranges``: by default they grow with the input, so that a range stays a small part of it;
    the result does not depend on their number.
    """
    ranges = max(RANGES, input_bytes(df) // RANGE_BYTES) if ranges is None else ranges
    size = words() if size is None else size
    base = df.select(F.col(id_col).alias("doc_id"), "source", size.alias("size"), F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit(""))).alias("place"))
    base = base.withColumn("bin", (F.conv(F.substring("place", 1, 8), 16, 10).cast("long") * ranges / F.lit(1 << 32)).cast("int"))
    # every text is read and counted once; all that follows works on these narrow rows
    base = written(base, scratch(df.sparkSession), "sizes")
    bins = base.groupBy("source", "bin").agg(F.sum("size").alias("bin_size"))
    sizes = bins.groupBy("source").agg(F.sum("bin_size").alias("source_size"))
    goal = targets(sizes, weights, share, rounds)
    up_to = W.partitionBy("source").orderBy("bin").rowsBetween(W.unboundedPreceding, -1)
    bins = bins.withColumn("bin_before", F.coalesce(F.sum("bin_size").over(up_to), F.lit(0)))
    same = lambda a, b, *more: [a["source"].eqNullSafe(b["source"]), *(a[k] == b[k] for k in more)]
    facts = bins.join(goal, same(bins, goal)).select(bins["source"], "bin", "bin_before", "source_size", "target")
    inside = W.partitionBy("source", "bin").orderBy("place", "size").rowsBetween(W.unboundedPreceding, 0)
    base = base.withColumn("inside", F.sum("size").over(inside))
    rows = base.join(facts, same(base, facts, "bin")).select("doc_id", "place", "size", "source_size", "target", (F.col("bin_before") + F.col("inside")).alias("run"))
    entry = rows.withColumn("round", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))))
    finish = (F.col("run") + F.col("round") * F.col("source_size")) / F.col("target")
    entry = entry.withColumn("finish", F.coalesce(F.when(F.col("target") > 0, finish), F.lit(0.0)))
    # All targets are met at time 1, so the cut lies near it; later times share the last slot.
    entry = entry.withColumn("slot", F.least(F.floor(F.col("finish") * ranges), F.lit(2 * ranges)).cast("int"))
    slots = entry.groupBy("slot").agg(F.sum("size").alias("slot_size"))
    along = W.orderBy("slot").rowsBetween(W.unboundedPreceding, -1)
    slots = slots.select("slot", "slot_size", F.coalesce(F.sum("slot_size").over(along), F.lit(0)).alias("slot_before"), (F.sum("slot_size").over(W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)) / rounds * share / 100.0).alias("budget"))
    # Whole slots under the budget need no order; the slot that crosses it is put in order.
    state = slots.select("slot", F.when(F.col("slot_before") + F.col("slot_size") <= F.col("budget"), 2).when(F.col("slot_before") < F.col("budget"), 1).otherwise(0).alias("state"), "slot_before", "budget")
    entry = entry.join(F.broadcast(state), "slot")
    edge = W.partitionBy("slot").orderBy("finish", "place", "round", "size").rowsBetween(W.unboundedPreceding, 0)
    crossing = entry.where("state = 1").withColumn("total", F.col("slot_before") + F.sum("size").over(edge))
    keys = ["doc_id", "place", "size", "run", "source_size", "target"]
    taken = entry.select(*keys, (F.col("state") == 2).cast("int").alias("hit")).where("hit = 1").unionByName(crossing.select(*keys, (F.col("total") <= F.col("budget")).cast("int").alias("hit")))
    rest = entry.where("state = 0").select(*keys, F.lit(0).alias("hit"))
    summed = taken.unionByName(rest).groupBy(*keys).agg(F.sum("hit").alias("hits"), F.count(F.lit(1)).alias("n"))
    # Rows alike in every respect meet in one group; each of them gets its own row again.
    alike = (F.col("n") / rounds).cast("int")
    each = summed.withColumn("k", F.explode(F.sequence(F.lit(0), alike - 1)))
    copies = F.least(F.lit(rounds), F.greatest(F.lit(0), F.col("hits") - F.col("k") * rounds))
    return each.select("doc_id", "size", "source_size", "target", copies.cast("int").alias("copies"), (copies * F.col("size")).cast("long").alias("taken"))


def mixed(df: DataFrame, **options) -> DataFrame:
    """df with each row as often as the mix takes it; rows that share an id go by the most of them."""
    id_col = options.get("id_col", "doc_id")
    chosen = plan(df, **options).groupBy(F.col("doc_id").alias("_mix_id")).agg(F.max("copies").alias("_mix_copies")).where("_mix_copies > 0")
    # the row travels as one value, so no column of it can clash with the mix's own
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("_mix_row"))
    joined = rows.join(chosen, F.col("_mix_row")[id_col].eqNullSafe(F.col("_mix_id")))
    return joined.withColumn("_mix_round", F.explode(F.sequence(F.lit(1), F.col("_mix_copies")))).select("_mix_row.*")


def op1_fair_queue_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plan(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


MIX_SQL = f"""
WITH docs AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
         md5(coalesce(doc_id::VARCHAR, '')) AS place FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM docs GROUP BY source),
w AS (SELECT source, source_size, [5, 2, 1][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1]::DOUBLE AS weight,
      source_size * {ROUNDS}.0::DOUBLE AS stop, (SELECT sum(source_size) FROM src)::DOUBLE * {SHARE} / 100 AS budget FROM src),
l AS (SELECT *, stop / weight AS ratio,
      (budget - coalesce(sum(stop) OVER (ORDER BY stop / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
      / sum(weight) OVER (ORDER BY stop / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
g AS (SELECT source, source_size, budget, coalesce(least(stop, weight * (SELECT max(level) FROM l)), stop) AS target FROM l),
r AS (SELECT doc_id, size, place, source_size, target, budget,
      sum(size) OVER (PARTITION BY docs.source ORDER BY place, size ROWS UNBOUNDED PRECEDING) AS run
      FROM docs JOIN g ON docs.source IS NOT DISTINCT FROM g.source),
e AS (SELECT *, CASE WHEN target > 0 THEN (run + k * source_size) / target ELSE 0 END AS finish FROM r, (SELECT unnest([0, 1]) AS k)),
t AS (SELECT *, sum(size) OVER (ORDER BY finish, place, k, size ROWS UNBOUNDED PRECEDING) AS total FROM e)
SELECT doc_id, size, source_size, target, sum(CASE WHEN total <= budget THEN size ELSE 0 END)::BIGINT AS taken
FROM t GROUP BY doc_id, size, place, source_size, target, run
"""
