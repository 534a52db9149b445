"""Layouts of a matrix, levels of its variables, and weighted row signatures."""

from __future__ import annotations

import math
import tempfile
import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.sources.workloads import Matrix

#: Variables that one signature mask holds.
MASK_BITS = 62


def cut(df: DataFrame) -> DataFrame:
    """End the lineage in the folder that all executors share."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp())
    return df.checkpoint()


def shared_folder(spark, name: str) -> str:
    """A fresh folder below spark.checkpoint.dir, which all executors share; local only where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or "file://" + tempfile.gettempdir()
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def weight(df: DataFrame) -> Column:
    """How many observations a row of cells stands for."""
    return F.col("w") if "w" in df.columns else F.lit(1)


def distinct_rows(matrix: Matrix) -> Matrix:
    """The same matrix with one obs for all observations that hold the same items, and their number as w.

    Rows that are at hand are counted before any shuffle by observation, so what moves and
    what follows grows with distinct rows.
    """
    rows = matrix.rows if matrix.rows is not None else matrix.cells.groupBy("obs").agg(F.collect_list("item").alias("items"))
    rows = rows.groupBy(F.array_sort("items").alias("items")).agg(F.count(F.lit(1)).alias("w"))
    numbered = cut(rows.withColumn("obs", F.monotonically_increasing_id()))
    return Matrix(numbered.select("obs", F.explode("items").alias("item"), "w"), matrix.n_obs)


def to_cells(df: DataFrame, key: str, cols: list[str]) -> DataFrame:
    """Wide to (key, variable, value); missing cells have no row."""
    kept = df.select(key, *[F.col(c).cast("double").alias(c) for c in cols])
    return kept.unpivot(key, cols, "variable", "value").where("value is not null and not isnan(value)")


def to_wide(cells: DataFrame, key: str, variables: list[str]) -> DataFrame:
    return cells.groupBy(key).pivot("variable", variables).agg(F.first("value", ignorenulls=True))


def explode_packed(df: DataFrame, key: str, array: str) -> DataFrame:
    return df.select(key, F.posexplode(array).alias("position", "value")).select(key, (F.col("position") + 1).alias("var_id"), F.col("value").cast("double").alias("value"))


def transpose_cells(cells: DataFrame, obs: str = "obs_id", var: str = "var_id") -> DataFrame:
    """Observations become variables and the other way round: only names change."""
    return cells.select(F.col(var).alias(obs), F.col(obs).alias(var), "value")


def to_presence(df: DataFrame, key: str, cols: list[str]) -> DataFrame:
    """One item for each column and level; missing cells have none."""
    each = F.array(*[F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in cols])
    return df.select(F.col(key).alias("obs"), F.explode(each).alias("item")).where("item is not null").distinct()


def equal_width(cells: DataFrame, bins: int, var: str = "variable") -> DataFrame:
    """level 0..bins-1 by each variable's range; one aggregation of a row a variable."""
    ends = cells.groupBy(var).agg(F.min("value").alias("lo"), F.max("value").alias("hi"))
    place = F.floor((F.col("value") - F.col("lo")) / (F.col("hi") - F.col("lo")) * bins)
    level = F.when(F.col("hi") == F.col("lo"), 0).otherwise(F.least(place, F.lit(bins - 1)))
    return cells.join(F.broadcast(ends), var).withColumn("level", level.cast("int")).drop("lo", "hi")


def equal_frequency(cells: DataFrame, bins: int, var: str = "variable", exact: bool = True) -> DataFrame:
    """level by quantile borders of each variable: how many borders are below or at the value."""
    steps = [i / bins for i in range(1, bins)]
    borders = F.percentile("value", F.array(*map(F.lit, steps))) if exact else F.percentile_approx("value", steps, 10000)
    of_var = cells.groupBy(var).agg(borders.alias("borders"))
    level = F.size(F.filter("borders", lambda b: b <= F.col("value")))
    return cells.join(F.broadcast(of_var), var).withColumn("level", level.cast("int")).drop("borders")


def signs(cells: DataFrame, least: float) -> DataFrame:
    """level 1 or -1 beyond a threshold, no row within it."""
    return cells.where(F.abs("value") > least).withColumn("level", F.when(F.col("value") > 0, 1).otherwise(-1))


def draw(items: DataFrame, n: int, run: int, seed: int = 42, name: str = "item") -> DataFrame:
    """A reproducible draw of n variables: the least by a digest of seed, run and name."""
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(str(run)), F.col(name)))
    return items.select(name).distinct().orderBy(key, name).limit(n)


def profile(cells: DataFrame, n_obs: int) -> DataFrame:
    """n_obs, n_vars and the share of missing cells in percent."""
    return cells.agg(F.count_distinct("item").alias("n_vars"), F.count(F.lit(1)).alias("n_cells")).select(
        F.lit(n_obs).cast("long").alias("n_obs"), "n_vars", F.round(100 * (1 - F.col("n_cells") / (F.lit(float(n_obs)) * F.col("n_vars"))), 6).alias("missing_pct")
    )


def top_variables(cells: DataFrame, k: int) -> DataFrame:
    """var_id 0..k-1 and item: the most frequent items, ties by name."""
    best = cells.groupBy("item").agg(F.count(F.lit(1)).alias("f")).orderBy(F.desc("f"), "item").limit(k)
    return best.select("item", (F.row_number().over(W.orderBy(F.desc("f"), "item")) - 1).alias("var_id"))


def numbered(items: DataFrame) -> DataFrame:
    """var_id 0.. by name: for a bounded set of drawn variables."""
    return items.select("item", (F.row_number().over(W.orderBy("item")) - 1).alias("var_id"))


def bit_of(place: str) -> Column:
    """A mask's bit of that place; a place that no mask holds ends the query with an error."""
    return F.expr(f"shiftleft(1L, cast(if({place} between 0 and {MASK_BITS - 1}, {place}, raise_error('a mask holds {MASK_BITS} variables; use plans.find or plans.wide')) as int))")


def signatures(cells: DataFrame, variables: DataFrame) -> DataFrame:
    """mask, w: distinct presence rows of the chosen variables (62 at most, more are an error) with their number.

    Rows without any of them are left out; N comes from the base table. Both shuffles
    carry partial aggregates, and the second has a row a distinct mask and task at most.
    """
    rows = cells.join(F.broadcast(variables), "item").groupBy("obs").agg(F.bit_or(bit_of("var_id")).alias("mask"))
    return rows.groupBy("mask").agg(F.count(F.lit(1)).alias("w"))


def cluster_signatures(cells: DataFrame, variables: DataFrame) -> DataFrame:
    """cluster_id, mask, w: signatures of every cluster of variables in one job.

    ``variables``: item, cluster_id, bit (place inside the cluster, so masks stay short
    however many variables there are).
    """
    rows = cells.join(F.broadcast(variables), "item").groupBy("cluster_id", "obs").agg(F.bit_or(bit_of("bit")).alias("mask"))
    return rows.groupBy("cluster_id", "mask").agg(F.count(F.lit(1)).alias("w"))


def bits(mask: Column | str) -> Column:
    """Places of a mask's ones, ascending."""
    m = F.col(mask) if isinstance(mask, str) else mask
    return F.filter(F.sequence(F.lit(0), F.lit(MASK_BITS - 1)), lambda i: F.getbit(m, i) == 1)


def as_text(mask: str = "mask") -> Column:
    """A pattern's variables, ascending, joined by commas."""
    return F.array_join(F.transform(bits(mask), lambda i: i.cast("string")), ",")


def cutoff(min_sup: float, n_obs: int) -> int:
    """Least count whose share of n_obs is strictly above min_sup, compared in doubles."""
    count = max(0, math.floor(min_sup * n_obs) - 1)
    while n_obs and not count / n_obs > min_sup:
        count += 1
    return max(1, count)


def cover(patterns: DataFrame, rows: DataFrame) -> DataFrame:
    """p, obs: the observations of each pattern; rows meet it on its lowest variable, then on all."""
    places = F.filter(F.sequence(F.lit(0), F.lit(MASK_BITS - 1)), lambda i: F.getbit("mask", i) == 1)
    spread = rows.select("obs", "mask", F.explode(places).alias("low"))
    asked = patterns.select(F.col("mask").alias("p"), F.expr("cast(log2(mask & -mask) as int)").alias("low"))
    return spread.join(asked, "low").where("(mask & p) = p").select("p", "obs")


def row_masks(cells: DataFrame, variables: DataFrame) -> DataFrame:
    return cells.join(F.broadcast(variables), "item").groupBy("obs").agg(F.bit_or(bit_of("var_id")).alias("mask"))
