"""Operators and functions around the methods (joins, aggregates, windows, sets, scalars)."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpatterns.operators import prepare as P
from vpatterns.operators import similarity as S
from vpatterns.queries import query
from vpatterns.queries import views as V
from vpatterns.queries.similar import BRAND_SQL, JOINT, SCORE, brand_cells
from vpatterns.sources import workloads as WL
from vpatterns.sources.tables import load


@query("scan_parquet_pruned", "SELECT l_returnflag, count(*)::BIGINT AS n FROM lineitem WHERE l_quantity > 45 GROUP BY 1")
def scan_parquet_pruned(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").where("l_quantity > 45").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("project_levels", "SELECT o_orderkey, CASE WHEN o_totalprice < 100000 THEN 'low' WHEN o_totalprice < 250000 THEN 'mid' ELSE 'high' END AS level FROM orders")
def project_levels(spark, sf_dir):
    p = F.col("o_totalprice")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.when(p < 100000, "low").when(p < 250000, "mid").otherwise("high").alias("level"))


@query("filter_missing", "SELECT p_partkey FROM part WHERE p_brand IN ('Brand#1', 'Brand#2') AND p_size BETWEEN 5 AND 30 AND p_type LIKE '%E%' AND p_name IS NOT NULL AND NOT (p_brand IS NOT DISTINCT FROM NULL)")
def filter_missing(spark, sf_dir):
    return load(spark, sf_dir, "part").where(F.col("p_brand").isin("Brand#1", "Brand#2") & F.col("p_size").between(5, 30) & F.col("p_type").like("%E%") & F.col("p_name").isNotNull() & ~F.col("p_brand").eqNullSafe(F.lit(None))).select("p_partkey")


@query("join_broadcast_profile", "SELECT n_name, count(*)::BIGINT AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def join_broadcast_profile(spark, sf_dir):
    nation = load(spark, sf_dir, "nation").select("n_nationkey", "n_name")  # 25 rows by its definition
    line, supplier = load(spark, sf_dir, "lineitem").select("l_suppkey"), load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    return line.join(supplier, line.l_suppkey == supplier.s_suppkey).join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@query("join_cells_pairs", f"WITH {V.BRANDS} SELECT a.item AS x, b.item AS y, count(*)::BIGINT AS n FROM it a JOIN it b ON a.obs = b.obs AND a.item < b.item GROUP BY 1, 2")
def join_cells_pairs(spark, sf_dir):
    c = WL.brands(spark, sf_dir).cells
    a, b = c.select("obs", F.col("item").alias("x")), c.select("obs", F.col("item").alias("y"))
    return a.hint("merge").join(b, "obs").where("x < y").groupBy("x", "y").agg(F.count(F.lit(1)).alias("n"))


@query("join_shuffle_hash", "SELECT o_orderpriority, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_shuffle_hash(spark, sf_dir):
    line, orders = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity"), load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    return line.join(orders.hint("shuffle_hash"), line.l_orderkey == orders.o_orderkey).groupBy("o_orderpriority").agg(F.sum("l_quantity").alias("q"))


@query("join_mask_theta", f"WITH {V.BRANDS}, {V.top(8)} SELECT p, count(*)::BIGINT AS n FROM sig, (SELECT unnest([3, 5, 6, 7]) AS p) WHERE (mask & p) = p GROUP BY p")
def join_mask_theta(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    sig = P.signatures(m.cells, P.top_variables(m.cells, 8))
    asked = spark.createDataFrame([(3,), (5,), (6,), (7,)], "p int")
    return sig.join(F.broadcast(asked), F.expr("(mask & p) = p")).groupBy("p").agg(F.count(F.lit(1)).alias("n"))


BINS = [(0, 0.0, 10.0), (1, 10.0, 25.0), (2, 25.0, 51.0)]


@query("join_bins_range", "SELECT b, count(*)::BIGINT AS n FROM lineitem JOIN (VALUES (0, 0.0, 10.0), (1, 10.0, 25.0), (2, 25.0, 51.0)) AS t(b, lo, hi) ON lo <= l_quantity AND l_quantity < hi GROUP BY b")
def join_bins_range(spark, sf_dir):
    bins = spark.createDataFrame(BINS, "b int, lo double, hi double")
    return load(spark, sf_dir, "lineitem").join(F.broadcast(bins), F.expr("lo <= l_quantity and l_quantity < hi")).groupBy("b").agg(F.count(F.lit(1)).alias("n"))


@query("join_asof_events", """SELECT e.event_id, max(p.event_id) AS purchase FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts < e.ts OR (p.ts = e.ts AND p.event_id < e.event_id)) WHERE e.event_type = 'error' GROUP BY e.event_id""")
def join_asof_events(spark, sf_dir):
    """The latest purchase of the same user before each error: one window, no range join."""
    e = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    before = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    got = e.withColumn("purchase", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(before))
    return got.where("event_type = 'error'").select("event_id", "purchase")


@query("join_interval_events", "SELECT a.event_type AS x, b.event_type AS y, count(*)::BIGINT AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1, 2")
def join_interval_events(spark, sf_dir):
    """Events of a user within an hour: equal hours and the next, then the exact bound."""
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.expr("cast(ts as timestamp)").alias("t"))
    e = e.withColumn("s", F.unix_micros("t")).withColumn("h", F.floor(F.col("s") / 3600e6))
    a = e.select("user_id", F.col("event_id").alias("i"), F.col("event_type").alias("x"), F.col("s").alias("s1"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    b = e.select("user_id", F.col("event_id").alias("j"), F.col("event_type").alias("y"), F.col("s").alias("s2"), "h")
    return a.join(b, ["user_id", "h"]).where("i < j and s2 >= s1 and s2 <= s1 + 3600000000").groupBy("x", "y").agg(F.count(F.lit(1)).alias("n"))


@query("join_semi_subset", f"WITH {V.BRANDS}, {V.top(8)}, {V.frequent(8, 0.02)}, two AS (SELECT DISTINCT a.mask | b.mask AS mask FROM freq a JOIN freq b ON a.mask < b.mask AND bit_count(a.mask) = 1 AND bit_count(b.mask) = 1) SELECT {V.text(k=8)} AS pattern FROM two WHERE mask IN (SELECT mask FROM freq)")
def join_semi_subset(spark, sf_dir):
    from vpatterns.operators import mining

    m = WL.brands(spark, sf_dir)
    found = mining.enumerate_patterns(P.signatures(m.cells, P.top_variables(m.cells, 8)), 8, P.cutoff(0.02, m.n_obs)).persist()
    one = found.where("bit_count(mask) = 1").select("mask")
    two = one.join(one.select(F.col("mask").alias("m2")), F.expr("mask < m2")).select(F.expr("mask | m2").alias("mask")).distinct()
    return two.join(found.select("mask"), "mask", "left_semi").select(P.as_text().alias("pattern"))


@query("join_anti_closed", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def join_anti_closed(spark, sf_dir):
    orders, line = load(spark, sf_dir, "orders").select("o_orderkey"), load(spark, sf_dir, "lineitem").select("l_orderkey")
    return orders.join(line, orders.o_orderkey == line.l_orderkey, "left_anti")


@query("join_outer_grid", f"WITH {BRAND_SQL}, g AS (SELECT o_orderkey AS obs, v FROM orders, (SELECT DISTINCT v FROM cells)) SELECT g.v::INT AS v, count(*) FILTER (WHERE l IS NULL)::BIGINT AS missing, count(l)::BIGINT AS present FROM g LEFT JOIN cells c ON c.obs = g.obs AND c.v = g.v GROUP BY g.v")
def join_outer_grid(spark, sf_dir):
    _, variables, cells = brand_cells(spark, sf_dir)
    grid = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("obs")).join(F.broadcast(variables.select("var_id")))
    got = grid.join(cells, ["obs", "var_id"], "left")
    return got.groupBy(F.col("var_id").alias("v")).agg(F.count_if(F.col("level").isNull()).alias("missing"), F.count("level").alias("present"))


@query("join_full_outer", "SELECT coalesce(c_nationkey, s_nationkey)::INT AS nation, coalesce(c, 0)::BIGINT AS customers, coalesce(s, 0)::BIGINT AS suppliers FROM (SELECT c_nationkey, count(*) AS c FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def join_full_outer(spark, sf_dir):
    c = load(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    s = load(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(s, "nation", "full").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("agg_marginals", f"WITH {BRAND_SQL}, {JOINT} SELECT v::INT AS v, l AS l, c::BIGINT AS c FROM s")
def agg_marginals(spark, sf_dir):
    return S.marginals(brand_cells(spark, sf_dir)[2])


@query("agg_distinct_levels", "SELECT count(DISTINCT p_brand)::BIGINT AS brands, count(DISTINCT p_type)::BIGINT AS types, count(DISTINCT (p_brand, p_type))::BIGINT AS both FROM part")
def agg_distinct_levels(spark, sf_dir):
    return load(spark, sf_dir, "part").agg(F.count_distinct("p_brand").alias("brands"), F.count_distinct("p_type").alias("types"), F.count_distinct("p_brand", "p_type").alias("both"))


@query("agg_distinct_approx")
def agg_distinct_approx(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_orderkey").alias("orders"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


@query("agg_stats", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_quantity, l_tax), 6) AS cov, round(var_pop(l_discount), 6) AS v, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
def agg_stats(spark, sf_dir):
    r = lambda c: F.round(c, 6)
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(r(F.corr("l_quantity", "l_extendedprice")).alias("r"), r(F.covar_samp("l_quantity", "l_tax")).alias("cov"), r(F.var_pop("l_discount")).alias("v"), r(F.stddev_samp("l_quantity")).alias("sd"))


@query("agg_quantiles", "SELECT p_brand, round(quantile_cont(p_retailprice, 0.5), 6) AS median, round(quantile_cont(p_retailprice, 0.9), 6) AS p90 FROM part GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    return load(spark, sf_dir, "part").groupBy("p_brand").agg(F.round(F.percentile("p_retailprice", 0.5), 6).alias("median"), F.round(F.percentile("p_retailprice", 0.9), 6).alias("p90"))


def _grouped(kind):
    def run(spark, sf_dir):
        o = load(spark, sf_dir, "orders").select("o_orderstatus", "o_orderpriority")
        return getattr(o, kind)("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))

    return run


query("agg_cube_levels", "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(_grouped("cube"))
query("agg_rollup_levels", "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")(_grouped("rollup"))
SETS = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"


@query("agg_grouping_sets", SETS.replace("count(*) AS n", "count(*)::BIGINT AS n"))
def agg_grouping_sets(spark, sf_dir):
    return spark.sql(SETS.replace("FROM orders", "FROM {orders}"), orders=load(spark, sf_dir, "orders"))


@query("agg_bitmap_support", f"WITH {V.BRANDS}, {V.top(8)}, c AS (SELECT obs, v FROM it JOIN vars USING (item)) SELECT a.v::INT AS a, b.v::INT AS b, count(*)::BIGINT AS support FROM c a JOIN c b ON a.obs = b.obs AND a.v < b.v GROUP BY 1, 2")
def agg_bitmap_support(spark, sf_dir):
    """Support of pairs from chunked bitmaps of observations: 32,768 bits a bucket."""
    _, _, cells = brand_cells(spark, sf_dir)
    maps = cells.select("var_id", F.bitmap_bucket_number("obs").alias("bucket"), F.bitmap_bit_position("obs").alias("bit")).groupBy("var_id", "bucket").agg(F.bitmap_construct_agg("bit").alias("map"))
    a, b = maps.select(F.col("var_id").alias("a"), "bucket", "map"), maps.select(F.col("var_id").alias("b"), "bucket", F.col("map").alias("map2"))
    both = a.join(b, "bucket").where("a < b")
    pair = both.select("a", "b", "bucket", F.explode(F.array("map", "map2")).alias("m")).groupBy("a", "b", "bucket").agg(F.expr("bitmap_count(bitmap_and_agg(m))").alias("n"))
    return pair.groupBy("a", "b").agg(F.sum("n").alias("support")).where("support > 0")


@query("win_rank_levels", """SELECT p_partkey, (row_number() OVER w)::INT AS rn, (rank() OVER r)::INT AS rk, (dense_rank() OVER r)::INT AS dr, round(percent_rank() OVER r, 6) AS pr, (ntile(4) OVER w)::INT AS nt, round(cume_dist() OVER r, 6) AS cd
FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), r AS (PARTITION BY p_brand ORDER BY p_size)""")
def win_rank_levels(spark, sf_dir):
    w, r = W.partitionBy("p_brand").orderBy("p_size", "p_partkey"), W.partitionBy("p_brand").orderBy("p_size")
    p = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_size")
    return p.select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(r).alias("rk"), F.dense_rank().over(r).alias("dr"), F.round(F.percent_rank().over(r), 6).alias("pr"), F.ntile(4).over(w).alias("nt"), F.round(F.cume_dist().over(r), 6).alias("cd"))


@query("win_lag_order", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, last_value(value) OVER f AS last, nth_value(value, 2) OVER f AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id), f AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_lag_order(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    f = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "value")
    return e.select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("value").over(w).alias("first"), F.last("value").over(f).alias("last"), F.nth_value("value", 2).over(f).alias("second"))


@query("win_frames", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS sliding, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)::BIGINT AS hour_before, count(*) OVER (PARTITION BY user_id)::BIGINT AS whole FROM events")
def win_frames(spark, sf_dir):
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    own = W.partitionBy("user_id")
    n = F.count(F.lit(1))
    return e.select("event_id", n.over(own.orderBy("ts", "event_id").rowsBetween(-2, 0)).alias("sliding"), n.over(own.orderBy("us").rangeBetween(-3600000000, 0)).alias("hour_before"), n.over(own).alias("whole"))


@query("topk_pairs", f"WITH {BRAND_SQL}, {JOINT}, {SCORE} SELECT a::INT AS a, b::INT AS b, round(purity * concentration, 6) AS sim FROM r ORDER BY round(purity * concentration, 9) DESC, a, b LIMIT 5")
def topk_pairs(spark, sf_dir):
    m, _, cells = brand_cells(spark, sf_dir)
    sim = S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs)
    return sim.orderBy(F.desc(F.round("sim", 9)), "a", "b").limit(5).select("a", "b", F.round("sim", 6).alias("sim"))


@query("topk_per_cluster", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def topk_per_cluster(spark, sf_dir):
    r = F.row_number().over(W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))
    return load(spark, sf_dir, "part").select("p_brand", "p_partkey", r.alias("r")).where("r <= 3").drop("r")


def _nations(spark, sf_dir):
    c = load(spark, sf_dir, "customer").where("c_acctbal > 9000").select(F.col("c_nationkey").alias("nation"))
    s = load(spark, sf_dir, "supplier").where("s_acctbal > 2000").select(F.col("s_nationkey").alias("nation"))
    return c, s


_C, _S = "SELECT c_nationkey AS nation FROM customer WHERE c_acctbal > 9000", "SELECT s_nationkey AS nation FROM supplier WHERE s_acctbal > 2000"
query("set_union", f"{_C} UNION {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].unionByName(_nations(spark, sf_dir)[1]).distinct())
query("set_intersect", f"{_C} INTERSECT {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].intersect(_nations(spark, sf_dir)[1]))
query("set_except", f"{_C} EXCEPT {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].subtract(_nations(spark, sf_dir)[1]))
query("set_union_all", f"{_C} UNION ALL {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].unionAll(_nations(spark, sf_dir)[1]))
query("set_except_all", f"{_C} EXCEPT ALL {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].exceptAll(_nations(spark, sf_dir)[1]))
query("set_intersect_all", f"{_C} INTERSECT ALL {_S}")(lambda spark, sf_dir: _nations(spark, sf_dir)[0].intersectAll(_nations(spark, sf_dir)[1]))


@query("fn_math_bits", "SELECT p_partkey, round(ln(p_size), 6) AS ln, round(log2(p_size), 6) AS lg, round(exp(p_size / 10.0::DOUBLE), 4) AS e, floor(p_retailprice)::BIGINT AS f, greatest(p_size, 10) AS g, bit_count(p_size)::INT AS b, (1::BIGINT << (p_size % 30)) AS s, p_size & 12 AS a, pow(p_size, 2) AS p FROM part")
def fn_math_bits(spark, sf_dir):
    return load(spark, sf_dir, "part").selectExpr("p_partkey", "round(ln(p_size), 6) as ln", "round(log2(p_size), 6) as lg", "round(exp(p_size / 10.0D), 4) as e", "cast(floor(p_retailprice) as bigint) as f", "greatest(p_size, 10) as g", "bit_count(p_size) as b", "shiftleft(1L, p_size % 30) as s", "p_size & 12 as a", "pow(p_size, 2) as p")


@query("fn_terms", "SELECT doc_id, len(regexp_extract_all(lower(text), '[a-z]+'))::INT AS n, md5(substring(text, 1, 20)) AS h, len(string_split(text, ' '))::INT AS parts, concat_ws('-', lang, source) AS k FROM documents")
def fn_terms(spark, sf_dir):
    d = load(spark, sf_dir, "documents")
    return d.select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0)).alias("n"), F.md5(F.substring("text", 1, 20)).alias("h"), F.size(F.split("text", " ")).alias("parts"), F.concat_ws("-", "lang", "source").alias("k"))


@query("fn_calendar_levels", "SELECT o_orderkey, hour(o_orderdate)::INT AS h, (dayofweek(o_orderdate) + 1)::INT AS d, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', TIMESTAMP '1990-01-01', o_orderdate)::INT AS days FROM orders")
def fn_calendar_levels(spark, sf_dir):
    t = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.hour(t).alias("h"), F.dayofweek(t).alias("d"), F.date_format(F.date_trunc("month", t), "yyyy-MM-dd").alias("m"), F.datediff(t, F.lit("1990-01-01").cast("date")).alias("days"))


@query("fn_array_patterns", """WITH {b}, r AS (SELECT obs, list(item ORDER BY item) AS l FROM it GROUP BY obs) SELECT obs, array_to_string(list_filter(l, lambda x: x IN ('Brand#1', 'Brand#2', 'Brand#3')), ',') AS common, len(list_distinct(list_concat(l, ['Brand#1', 'Brand#99'])))::INT AS n_union, list_contains(l, 'Brand#5') AS has, list_sum(list_transform(l, lambda x: len(x)))::BIGINT AS letters FROM r""".replace("{b}", V.BRANDS))
def fn_array_patterns(spark, sf_dir):
    rows = WL.brands(spark, sf_dir).cells.groupBy("obs").agg(F.array_sort(F.collect_list("item")).alias("l"))
    some = F.array(*map(F.lit, ("Brand#1", "Brand#2", "Brand#3")))
    letters = F.aggregate("l", F.lit(0).cast("long"), lambda a, x: a + F.length(x))
    return rows.select("obs", F.array_join(F.array_intersect("l", some), ",").alias("common"), F.size(F.array_union("l", F.array(F.lit("Brand#1"), F.lit("Brand#99")))).alias("n_union"), F.exists("l", lambda x: x == "Brand#5").alias("has"), letters.alias("letters"))


@query("fn_array_windows", f"WITH {BRAND_SQL} SELECT obs, array_to_string(list_transform(list(v ORDER BY v), lambda x: x * 2), ',') AS twice, min(v)::INT AS low, max(v)::INT AS high FROM cells GROUP BY obs")
def fn_array_windows(spark, sf_dir):
    rows = brand_cells(spark, sf_dir)[2].groupBy("obs").agg(F.array_sort(F.collect_list("var_id")).alias("l"))
    twice = F.zip_with("l", "l", lambda x, y: x + y)
    return rows.select("obs", F.array_join(F.transform(twice, lambda x: x.cast("string")), ",").alias("twice"), F.array_min("l").alias("low"), F.array_max("l").alias("high"))


@query("fn_map_pattern", "SELECT p_partkey, k AS key, CASE k WHEN 'size' THEN p_size::DOUBLE WHEN 'price' THEN p_retailprice END AS value FROM part, (SELECT unnest(['size', 'price']) AS k) WHERE CASE k WHEN 'size' THEN p_size::DOUBLE ELSE p_retailprice END > 20")
def fn_map_pattern(spark, sf_dir):
    m = F.map_concat(F.map_from_arrays(F.array(F.lit("size")), F.array(F.col("p_size").cast("double"))), F.create_map(F.lit("price"), F.col("p_retailprice")))
    return load(spark, sf_dir, "part").select("p_partkey", F.explode(F.map_entries(F.map_filter(m, lambda k, v: v > 20))).alias("e")).select("p_partkey", "e.key", "e.value")


@query("fn_json_props", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k, json_valid(props) AS ok FROM events")
def fn_json_props(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").isNotNull().alias("ok"))


@query("fn_nulls", "SELECT l_orderkey, l_linenumber, l_partkey, coalesce(nullif(l_tax, 0), -1) AS tax, CASE WHEN nullif(l_discount, 0) IS NULL THEN 'none' ELSE 'some' END AS d FROM lineitem")
def fn_nulls(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.coalesce(F.nullif(F.col("l_tax"), F.lit(0.0)), F.lit(-1.0)).alias("tax"), F.nvl2(F.nullif(F.col("l_discount"), F.lit(0.0)), F.lit("some"), F.lit("none")).alias("d"))
