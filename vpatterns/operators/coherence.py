"""Coherence of given biclusters, and miners for additive, multiplicative and ordered patterns.

Biclusters come as cells (bicluster_id, obs_id, var_id, value).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.operators.mining import containing
from vpatterns.operators.prepare import cut

B = "bicluster_id"


def _verdict(residuals: DataFrame, eps: float) -> DataFrame:
    top = residuals.groupBy(B).agg(F.max("r").alias("max_residual"))
    return top.select(B, (F.col("max_residual") <= eps).alias("holds"), "max_residual")


def constant_overall(cells: DataFrame, eps: float = 1e-9) -> DataFrame:
    spread = cells.groupBy(B).agg((F.max("value") - F.min("value")).alias("r"))
    return _verdict(spread, eps)


def constant_on_variables(cells: DataFrame, eps: float = 1e-9) -> DataFrame:
    return _verdict(cells.groupBy(B, "var_id").agg((F.max("value") - F.min("value")).alias("r")), eps)


def _residual(cells: DataFrame) -> DataFrame:
    row, col, all_ = W.partitionBy(B, "obs_id"), W.partitionBy(B, "var_id"), W.partitionBy(B)
    fitted = F.avg("value").over(row) + F.avg("value").over(col) - F.avg("value").over(all_)
    return cells.withColumn("r", F.abs(F.col("value") - fitted))


def additive(cells: DataFrame, eps: float = 1e-9) -> DataFrame:
    return _verdict(_residual(cells), eps)


def multiplicative(cells: DataFrame, eps: float = 1e-9) -> DataFrame:
    """On positive values, additive in logarithms; a bicluster with others does not hold."""
    logs = _residual(cells.withColumn("value", F.when(F.col("value") > 0, F.log("value"))))
    bad = cells.groupBy(B).agg(F.min("value").alias("low"))
    got = _verdict(logs, eps).join(bad, B)
    return got.select(B, (F.col("holds") & (F.col("low") > 0)).alias("holds"), F.when(F.col("low") > 0, F.col("max_residual")).alias("max_residual"))


def order_preserving(cells: DataFrame, axis: str = "vars", strict: bool = True) -> DataFrame:
    """Whether one order of the variables (or observations) ranks every line of values.

    The order can only be that of the values' means, so each line is compared with it.
    """
    line, item = ("obs_id", "var_id") if axis == "vars" else ("var_id", "obs_id")
    mean = cells.groupBy(B, item).agg(F.avg("value").alias("m"))
    along = W.partitionBy(B, line).orderBy("m", item)
    step = cells.join(mean, [B, item]).withColumn("prev", F.lag("value").over(along))
    wrong = F.col("prev") >= F.col("value") if strict else F.col("prev") > F.col("value")
    bad = step.groupBy(B).agg(F.max(F.when(wrong, F.col("prev") - F.col("value")).otherwise(F.lit(0.0))).alias("max_residual"), F.max(F.when(wrong, 1).otherwise(0)).alias("bad"))
    return bad.select(B, (F.col("bad") == 0).alias("holds"), "max_residual")


def fit_pattern(cells: DataFrame, kind: str = "additive") -> DataFrame:
    """bicluster_id, var_id, mu, noise: expected values and mean absolute rest of each variable.

    For additive coherence mu is the variable's mean over the bicluster, the row
    adjustments having mean 0; for constant coherence the variable's mean.
    """
    col = W.partitionBy(B, "var_id")
    mu = F.avg("value").over(col)
    gamma = F.avg("value").over(W.partitionBy(B, "obs_id")) - F.avg("value").over(W.partitionBy(B)) if kind == "additive" else F.lit(0.0)
    rest = cells.withColumn("mu", mu).withColumn("noise", F.abs(F.col("value") - F.col("mu") - gamma))
    return rest.groupBy(B, "var_id").agg(F.first("mu").alias("mu"), F.avg("noise").alias("noise"))


def merit_variance(cells: DataFrame) -> DataFrame:
    return cells.groupBy(B).agg(F.var_pop("value").alias("merit"))


def bicluster_maximal(patterns: DataFrame, sig: DataFrame, n_vars: int) -> DataFrame:
    """mask, support, maximal: no variable can join without losing a row.

    Rows cannot be added to a pattern that takes all rows that hold it.
    """
    asked = cut(patterns.select("mask").distinct())
    common = containing(asked, sig, n=asked.count()).groupBy(F.col("_mask").alias("p")).agg(F.sum("w").alias("support"), F.bit_and("mask").alias("shared"))
    return common.select(F.col("p").alias("mask"), "support", F.expr("shared = p").alias("maximal"))


#: Whole numbers up to this size have ratios that are one double if and only if they are equal.
EXACT_RATIO = 1 << 26


def ratio(y: str, x: str):
    """y / x of whole numbers as a double that stands for the reduced fraction.

    Division rounds correctly, so equal fractions give one double; different ones of
    numbers up to EXACT_RATIO lie further apart than a double's step. Larger numbers end
    the query with an error.
    """
    fits = (F.abs(F.col(x)) <= EXACT_RATIO) & (F.abs(F.col(y)) <= EXACT_RATIO)
    return F.when(fits, F.col(y).cast("double") / F.col(x).cast("double")).otherwise(F.raise_error(F.lit("ratios need values up to 2**26: use a coarser grid")).cast("double"))


def pivot_differences(values: DataFrame, kind: str = "additive") -> DataFrame:
    """obs, pivot, var, d: for every pivot, the difference (ratio) of each later variable to it."""
    x = values.select("obs", F.col("var").alias("pivot"), F.col("value").alias("x"))
    y = values.select("obs", "var", F.col("value").alias("y"))
    both = x.join(y, "obs").where("pivot < var")
    if kind == "additive":
        return both.select("obs", "pivot", "var", (F.col("y") - F.col("x")).cast("double").alias("d"))
    return both.where("x <> 0 and y <> 0").select("obs", "pivot", "var", ratio("y", "x").alias("d"))


def mine_offsets(values: DataFrame, least: int, kind: str = "additive", max_len: int | None = None) -> DataFrame:
    """vars, offsets, support of all additive (multiplicative) patterns of two variables or more.

    A pattern is its least variable, the pivot, and constant differences of others to it;
    it grows by one later variable at a time over the rows that still hold it.
    """
    d = pivot_differences(values, kind)
    often = d.groupBy("pivot", "var", "d").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
    d = cut(d.join(often.drop("support"), ["pivot", "var", "d"], "left_semi"))
    zero = 0.0 if kind == "additive" else 1.0
    held = d.select("obs", F.array("pivot", "var").alias("vars"), F.array(F.lit(zero), F.col("d")).alias("offsets"), "pivot", F.col("var").alias("last"))
    found = held.groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support"))
    size = 2
    while max_len is None or size < max_len:
        more = d.select("obs", "pivot", "var", "d")
        longer = held.join(more, ["obs", "pivot"]).where("var > last").select("obs", F.array_append("vars", F.col("var")).alias("vars"), F.array_append("offsets", F.col("d")).alias("offsets"), "pivot", F.col("var").alias("last"))
        kept = longer.groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
        held = cut(longer.join(kept.drop("support"), ["vars", "offsets"], "left_semi"))
        if not held.limit(1).count():
            break
        found = found.unionByName(held.groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support")))
        size += 1
    return found.where(F.col("support") >= least)


def closed_offsets(patterns: DataFrame, kind: str = "additive") -> DataFrame:
    """Patterns that no longer one of the same support encloses, offsets taken from the pivot.

    A longer pattern encloses a shorter one on its last variable; they meet on it.
    """
    tagged = patterns.withColumn("map", F.map_from_arrays("vars", "offsets")).withColumn("k", F.element_at("vars", -1))
    other = tagged.select(F.col("vars").alias("v2"), F.col("map").alias("o2"), F.col("support").alias("s2"), F.explode("vars").alias("k2"))
    inside = F.size(F.array_except("vars", "v2")) == 0
    base = F.col("o2")[F.col("vars")[0]]
    rest = lambda v: F.abs(F.col("o2")[v] - base - F.col("map")[v]) if kind == "additive" else F.abs(F.col("o2")[v] / base / F.col("map")[v] - 1)
    same = F.forall("vars", lambda v: rest(v) < (1e-6 if kind == "additive" else 1e-12))
    cond = (F.col("support") == F.col("s2")) & (F.col("k") == F.col("k2")) & (F.size("vars") < F.size("v2")) & inside & same
    return tagged.join(other, cond, "left_anti").drop("map", "k")


def mine_order(values: DataFrame, least: int, max_len: int | None = None) -> DataFrame:
    """seq (variables by rising value), support of all ordered patterns of two variables or more."""
    v = values.select("obs", "var", "value")
    held = v.select("obs", F.array("var").alias("seq"), F.col("value").alias("top"))
    found, size = None, 1
    while max_len is None or size < max_len:
        longer = held.join(v, "obs").where("value > top").select("obs", F.array_append("seq", F.col("var")).alias("seq"), F.col("value").alias("top"))
        kept = longer.groupBy("seq").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
        kept = cut(kept)
        if not kept.limit(1).count():
            break
        held = cut(longer.join(kept.drop("support"), "seq", "left_semi"))
        found = kept if found is None else found.unionByName(kept)
        size += 1
    return found if found is not None else held.select("seq", F.lit(0).cast("long").alias("support")).limit(0)


def order_sequences(values: DataFrame) -> DataFrame:
    """obs, sequence: variables by value, those with one value in one element."""
    ties = values.groupBy("obs", "value").agg(F.array_sort(F.collect_list("var")).alias("same"))
    return ties.groupBy("obs").agg(F.array_sort(F.collect_list(F.struct("value", "same"))).alias("s")).select("obs", F.transform("s", lambda x: x["same"]).alias("sequence"))


def prefixspan(values: DataFrame, least: int, n_obs: int, max_len: int | None = None) -> DataFrame:
    """The same patterns as ``mine_order`` by the library's sequence miner, of any length.

    A pattern has each variable once, so none is longer than the number of variables.
    """
    from pyspark.ml.fpm import PrefixSpan

    rows = order_sequences(values)
    longest = max_len if max_len is not None else max(1, values.select("var").distinct().count())
    got = PrefixSpan(minSupport=(least - 0.5) / n_obs, maxPatternLength=longest).findFrequentSequentialPatterns(rows)
    single = got.where(F.forall("sequence", lambda s: F.size(s) == 1) & (F.size("sequence") > 1))
    return single.select(F.flatten("sequence").alias("seq"), F.col("freq").alias("support"))


def merge_offset(left: DataFrame, right: DataFrame, least: int, kind: str = "additive") -> DataFrame:
    """Common rows of two groups' patterns, split by the difference (ratio) of their pivots.

    ``left`` and ``right`` hold (obs, vars, offsets, base): the rows of each pattern with
    its pivot's value. Plain intersection would join rows whose pivots differ unequally.
    """
    a = left.select("obs", F.col("vars").alias("v1"), F.col("offsets").alias("o1"), F.col("base").alias("b1"))
    b = right.select("obs", F.col("vars").alias("v2"), F.col("offsets").alias("o2"), F.col("base").alias("b2"))
    shift = F.col("b2") - F.col("b1") if kind == "additive" else ratio("b2", "b1")
    met = a.join(b, "obs").withColumn("shift", shift)
    kept = met.groupBy("v1", "o1", "v2", "o2", "shift").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
    # a ratio is taken again from the whole numbers themselves, so it is the exact one
    moved = (lambda o: o + F.col("shift")) if kind == "additive" else (lambda o: F.rint(o * F.col("b2")) / F.col("b1"))
    both = F.concat("o1", F.transform("o2", moved))
    rows = met.join(kept.drop("support"), ["v1", "o1", "v2", "o2", "shift"], "left_semi")
    return rows.select("obs", F.concat("v1", "v2").alias("vars"), both.alias("offsets"), F.col("b1").alias("base"))


def offset_rows(values: DataFrame, patterns: DataFrame, kind: str = "additive") -> DataFrame:
    """obs, vars, offsets, base of every row that holds one of the patterns; single variables hold all.

    For ratios, values of 0 belong to no pattern.
    """
    values = values if kind == "additive" else values.where("value <> 0")
    x = values.groupBy("obs").agg(F.map_from_entries(F.collect_list(F.struct("var", "value"))).alias("m"))
    base = F.col("m")[F.col("vars")[0]]
    of = (lambda v: (v - base).cast("double")) if kind == "additive" else (lambda v: v.cast("double") / base.cast("double"))
    holds = F.forall(F.arrays_zip("vars", "offsets"), lambda t: F.coalesce(of(F.col("m")[t["vars"]]) == t["offsets"], F.lit(False)))
    # every pattern has a pivot and a first difference: rows meet it on these, then on the rest
    first = patterns.select("vars", "offsets", F.col("vars")[0].alias("pivot"), F.col("vars")[1].alias("var"), F.col("offsets")[1].alias("d"))
    met = pivot_differences(values, kind).join(first, ["pivot", "var", "d"]).select("obs", "vars", "offsets")
    found = met.join(x, "obs").where(holds).select("obs", "vars", "offsets", base.cast("double").alias("base"))
    zero = 0.0 if kind == "additive" else 1.0
    single = values.select("obs", F.array("var").alias("vars"), F.array(F.lit(zero)).alias("offsets"), F.col("value").cast("double").alias("base"))
    return found.unionByName(single)


def merge_order(left: DataFrame, right: DataFrame, values: DataFrame, least: int) -> DataFrame:
    """seq, support: common rows of two groups' ordered patterns, split by how they interleave.

    All frequent patterns of both groups are needed, closed ones are not enough.
    """
    x = values.groupBy("obs").agg(F.map_from_entries(F.collect_list(F.struct("var", "value"))).alias("m"))

    def rows(p: DataFrame, name: str) -> DataFrame:
        held = _rows_in_order(values, x, p)
        short = p.where(F.size("seq") == 1).select("seq", F.col("seq")[0].alias("var"))
        one = values.select("obs", "var").join(short, "var").select("obs", "seq")
        return held.unionByName(one).withColumnRenamed("seq", name)

    both = rows(left, "s1").join(rows(right, "s2"), "obs").join(x, "obs")
    inter = F.array_sort(F.transform(F.concat("s1", "s2"), lambda v: F.struct(F.col("m")[v].alias("k"), v.alias("v"))))
    both = both.withColumn("t", inter).where(F.size("t") == F.size(F.array_distinct(F.transform("t", lambda x: x["k"]))))
    return both.select("obs", F.transform("t", lambda x: x["v"]).alias("seq")).distinct().groupBy("seq").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)


def from_least(patterns: DataFrame, kind: str = "additive") -> DataFrame:
    """vars ascending, offsets to the least variable: patterns of merged groups in one form."""
    pairs = F.array_sort(F.arrays_zip("vars", "offsets"))
    base = F.col("p")[0]["offsets"]
    to = (lambda x: x["offsets"] - base) if kind == "additive" else (lambda x: x["offsets"] / base)
    return patterns.withColumn("p", pairs).select(F.transform("p", lambda x: x["vars"]).alias("vars"), F.transform("p", to).alias("offsets"), "support")


def order_rows(values: DataFrame, patterns: DataFrame) -> DataFrame:
    """obs, seq: the rows of given ordered patterns; they meet on the first two variables, then on the rest."""
    x = values.groupBy("obs").agg(F.map_from_entries(F.collect_list(F.struct("var", "value"))).alias("m"))
    return _rows_in_order(values, x, patterns)


def order_support(values: DataFrame, patterns: DataFrame, least: int) -> DataFrame:
    """seq, support of given ordered patterns."""
    return order_rows(values, patterns).groupBy("seq").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)


def _rows_in_order(values: DataFrame, maps: DataFrame, patterns: DataFrame) -> DataFrame:
    """obs, seq of the rows that hold patterns of two variables or more."""
    y = values.select("obs", F.col("var").alias("b"), F.col("value").alias("vb"))
    rising = values.select("obs", F.col("var").alias("a"), F.col("value").alias("va")).join(y, "obs").where("va < vb").select("obs", "a", "b")
    pairs = F.forall(F.sequence(F.lit(1), F.size("seq") - 1), lambda i: F.coalesce(F.col("m")[F.col("seq")[i - 1]] < F.col("m")[F.col("seq")[i]], F.lit(False)))
    long = patterns.where(F.size("seq") > 1).select("seq", F.col("seq")[0].alias("a"), F.col("seq")[1].alias("b"))
    return rising.join(long, ["a", "b"]).join(maps, "obs").where(pairs).select("obs", "seq")
