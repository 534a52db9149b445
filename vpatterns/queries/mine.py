"""Mining, merging, closedness, the pipeline and its experiment (M-13..35, B-07..09, C-, R-, W- keys)."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from vpatterns.functions import significance as G
from vpatterns.operators import clustering, mining
from vpatterns.operators import coherence as H
from vpatterns.operators import merge as M
from vpatterns.operators import prepare as P
from vpatterns.operators.closed import closed_by_length, number_of_closed
from vpatterns.plans import experiment as X
from vpatterns.plans import pipeline as D
from vpatterns.plans.find import find
from vpatterns.plans.kinds import discover_kind
from vpatterns.plans.wide import closed_local, discover_wide, placed_variables, weighted_rows
from vpatterns.queries import query
from vpatterns.queries import views as V
from vpatterns.queries.similar import JOINT, RANDOM, SCORE
from vpatterns.sources import workloads as WL
from vpatterns.sources.tables import load

K, MS = 12, 0.001
BRAND_ALL = V.patterns(V.BRANDS, K, MS, "all")
BRAND_CLOSED = V.patterns(V.BRANDS, K, MS)


def brand_signatures(spark, sf_dir, k=K):
    m = WL.brands(spark, sf_dir)
    variables = P.top_variables(m.cells, k)
    return m, variables, P.cut(P.signatures(m.cells, variables)), P.cutoff(MS, m.n_obs)


@query("enumerate_12", BRAND_ALL)
def enumerate_12(spark, sf_dir):
    _, _, sig, least = brand_signatures(spark, sf_dir)
    return D.contract(mining.enumerate_patterns(sig, K, least))


@query("apriori_order_brand", BRAND_ALL)
def apriori_order_brand(spark, sf_dir):
    _, _, sig, least = brand_signatures(spark, sf_dir)
    return D.contract(mining.apriori(sig, least))


@query("apriori_lineitem", V.patterns(V.W3, K, 0.01, "all"))
def apriori_lineitem(spark, sf_dir):
    m = WL.line_attributes(spark, sf_dir)
    sig = P.signatures(m.cells, P.top_variables(m.cells, K))
    return D.contract(mining.apriori(sig, P.cutoff(0.01, m.n_obs)))


@query("fpgrowth_order_brand", BRAND_ALL)
def fpgrowth_order_brand(spark, sf_dir):
    m, variables, _, _ = brand_signatures(spark, sf_dir)
    cells = m.cells.join(F.broadcast(variables), "item").select("obs", F.col("var_id").cast("int").alias("item"))
    got = mining.fpgrowth(cells, m.n_obs, MS)
    text = F.array_join(F.transform(F.array_sort("items"), lambda i: i.cast("string")), ",")
    return got.select(text.alias("pattern"), F.size("items").alias("n_vars"), F.col("freq").cast("long").alias("support"))


@query("frequent_items", f"WITH {V.BRANDS} SELECT item, count(*)::BIGINT AS support FROM it GROUP BY item HAVING count(*) / (SELECT n FROM n) > 0.1")
def frequent_items(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    return mining.frequent_items(m.cells, P.cutoff(0.1, m.n_obs))


# Groups of variables by a digest of their names, so that SQL knows them too.
PARTS_SQL = f"""WITH {V.BRANDS},
{V.top(K)}, {RANDOM}, own AS (SELECT c, sum(1::BIGINT << v::INT)::BIGINT AS own FROM rc GROUP BY c),
{V.frequent(K, MS)},
loc AS (SELECT c::INT AS cluster_id, mask, support FROM freq JOIN own ON (mask & own) = mask)"""


def local(spark, sf_dir, closed):
    m, variables, sig, least = brand_signatures(spark, sf_dir)
    return m, sig, least, D.local_patterns(sig, clustering.random_clusters(variables, 4), least, closed)


@query("partition_patterns", f"{PARTS_SQL} SELECT cluster_id, {V.text(k=K)} AS pattern, support FROM loc")
def partition_patterns(spark, sf_dir):
    return local(spark, sf_dir, False)[3].select("cluster_id", P.as_text().alias("pattern"), "support")


@query("partition_closed", f"{PARTS_SQL} SELECT cluster_id, {V.text(k=K)} AS pattern, support FROM loc a WHERE NOT EXISTS (SELECT 1 FROM loc b WHERE b.cluster_id = a.cluster_id AND b.support = a.support AND a.mask <> b.mask AND (a.mask & b.mask) = a.mask)")
def partition_closed(spark, sf_dir):
    return local(spark, sf_dir, True)[3].select("cluster_id", P.as_text().alias("pattern"), "support")


@query("partition_signatures", f"WITH {V.BRANDS}, {V.top(K)}, {RANDOM}, own AS (SELECT c, v, row_number() OVER (PARTITION BY c ORDER BY v) - 1 AS bit FROM rc), r AS (SELECT c, obs, sum(1::BIGINT << bit::INT)::BIGINT AS mask FROM it JOIN vars USING (item) JOIN own USING (v) GROUP BY c, obs) SELECT c::INT AS cluster_id, mask, count(*)::BIGINT AS w FROM r GROUP BY c, mask")
def partition_signatures(spark, sf_dir):
    from pyspark.sql import Window as W

    m, variables, _, _ = brand_signatures(spark, sf_dir)
    groups = variables.join(clustering.random_clusters(variables, 4), "var_id")
    placed = groups.select("item", "cluster_id", (F.row_number().over(W.partitionBy("cluster_id").orderBy("var_id")) - 1).alias("bit"))
    return P.cluster_signatures(m.cells, placed)


def _merged(how):
    def run(spark, sf_dir):
        _, sig, least, parts = local(spark, sf_dir, True)
        parts = P.cut(parts)
        ids = [r["cluster_id"] for r in parts.select("cluster_id").distinct().orderBy("cluster_id").collect()]
        frames = [parts.where(F.col("cluster_id") == c).select("mask", "support") for c in ids]
        got = how(frames, sig, least)
        return D.contract(got[0] if isinstance(got, tuple) else got)

    return run


for _name, _how in (("merge_sequential", M.merge_sequential), ("merge_tree", M.merge_tree), ("merge_membership", M.merge_membership)):
    query(_name, BRAND_CLOSED)(_merged(_how))


@query("closed_global", BRAND_CLOSED)
def closed_global(spark, sf_dir):
    m, variables, _, _ = brand_signatures(spark, sf_dir)
    return D.contract(D.discover_global(m, variables, MS))


# Patterns of users by hour: far fewer are closed than frequent.
def hour_signatures(spark, sf_dir, k=10):
    m = WL.user_event_hours(spark, sf_dir)
    sig = P.cut(P.signatures(m.cells, P.top_variables(m.cells, k)))
    return m, sig, mining.enumerate_patterns(sig, k, P.cutoff(0.01, m.n_obs))


@query("closed_pairwise", V.patterns(V.W7, 10, 0.01))
def closed_pairwise(spark, sf_dir):
    return D.contract(M.closed_pairwise(hour_signatures(spark, sf_dir)[2]))


@query("closed_collapse", V.patterns(V.W7, 10, 0.01))
def closed_collapse(spark, sf_dir):
    _, sig, found = hour_signatures(spark, sf_dir)
    return D.contract(M.closed_collapse(found, sig))


@query("maximal_patterns", V.patterns(V.BRANDS, K, MS, "maximal"))
def maximal_patterns(spark, sf_dir):
    _, _, sig, least = brand_signatures(spark, sf_dir)
    return D.contract(M.maximal(mining.enumerate_patterns(sig, K, least)))


@query("merge_vs_global", "SELECT 0::BIGINT AS missing, 0::BIGINT AS extra")
def merge_vs_global(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    variables = P.top_variables(m.cells, 8)
    found = D.discover(m, variables, MS).patterns
    return M.verify_complete(found, D.discover_global(m, variables, MS))


@query("overlap_filter", f"""WITH {V.BRANDS}, {V.top(8)}, {V.frequent(8, 0.02)}, a AS (SELECT mask, support, bit_count(mask) * support AS area FROM freq),
p AS (SELECT x.mask, x.area, y.mask AS m2, y.area AS a2 FROM a x JOIN a y ON (x.mask & y.mask) <> 0 AND (y.area > x.area OR (y.area = x.area AND y.mask < x.mask))),
c AS (SELECT p.mask, p.m2, p.area, p.a2, coalesce(sum(w), 0) * bit_count(p.mask & p.m2) AS shared FROM p LEFT JOIN sig ON (sig.mask & (p.mask | p.m2)) = (p.mask | p.m2) GROUP BY p.mask, p.m2, p.area, p.a2)
SELECT {V.text(k=8)} AS pattern, bit_count(mask)::INT AS n_vars, support FROM freq WHERE mask NOT IN (SELECT mask FROM c WHERE shared / (area + a2 - shared)::DOUBLE > 0.1)""")
def overlap_filter(spark, sf_dir):
    m, _, sig, _ = brand_signatures(spark, sf_dir, 8)
    found = mining.enumerate_patterns(sig, 8, P.cutoff(0.02, m.n_obs))
    return D.contract(M.drop_overlapping(found, sig, 0.1))


@query("pattern_support", f"WITH {V.BRANDS}, {V.top(K)} SELECT p, bit_count(p)::INT AS length, coalesce(sum(w), 0)::BIGINT AS support FROM (SELECT unnest([3, 5, 7, 9, 1023]) AS p) LEFT JOIN sig ON (mask & p) = p GROUP BY p")
def pattern_support(spark, sf_dir):
    _, _, sig, _ = brand_signatures(spark, sf_dir)
    asked = spark.createDataFrame([(3,), (5,), (7,), (9,), (1023,)], "p int")
    got = mining.support(asked.select(F.col("p").cast("long").alias("mask")), sig)
    return asked.join(got, asked.p == got.mask, "left").select("p", F.bit_count("p").alias("length"), F.coalesce("support", F.lit(0)).cast("long").alias("support"))


@query("bicluster_maximal", f"WITH {V.W7}, {V.top(10)}, {V.frequent(10, 0.01)} SELECT {V.text('a.mask', 10)} AS pattern, support, NOT EXISTS (SELECT 1 FROM (SELECT unnest(range(0, 10)) AS i) WHERE (a.mask >> i::INT) & 1 = 0 AND (SELECT coalesce(sum(w), 0) FROM sig WHERE (sig.mask & (a.mask | (1::BIGINT << i::INT))) = (a.mask | (1::BIGINT << i::INT))) = a.support) AS maximal FROM freq a")
def bicluster_maximal(spark, sf_dir):
    _, sig, found = hour_signatures(spark, sf_dir)
    return H.bicluster_maximal(found, sig, 10).select(P.as_text().alias("pattern"), F.col("support").cast("long").alias("support"), "maximal")


def _pipeline(strategy, merge="sequential"):
    def run(spark, sf_dir):
        m = WL.brands(spark, sf_dir)
        return D.contract(D.discover(m, P.top_variables(m.cells, K), MS, strategy=strategy, merge=merge).patterns)

    return run


for _s in D.STRATEGIES:
    query(f"pipeline_{_s}", BRAND_CLOSED)(_pipeline(_s))


def flagship(spark, sf_dir):
    """Eight brands: similarity, groups of four, mining, merging, closed patterns."""
    m = WL.brands(spark, sf_dir)
    return D.contract(D.discover(m, P.top_variables(m.cells, 8), MS).patterns)


query("entry", V.patterns(V.BRANDS, 8, MS))(flagship)


@query("related_horizontal", BRAND_ALL)
def related_horizontal(spark, sf_dir):
    m, _, sig, _ = brand_signatures(spark, sf_dir)
    return D.contract(mining.mine_horizontal(sig, 2, m.n_obs, MS))


@query("related_prefix", BRAND_ALL)
def related_prefix(spark, sf_dir):
    _, _, sig, least = brand_signatures(spark, sf_dir)
    return D.contract(mining.mine_by_prefix(sig, least))


@query("related_sample")
def related_sample(spark, sf_dir):
    m, _, sig, _ = brand_signatures(spark, sf_dir)
    return D.contract(mining.sample_mine(sig, 0.5, m.n_obs, 0.005))


@query("related_sample_recall")
def related_sample_recall(spark, sf_dir):
    """How many of the exact patterns the sample gives."""
    m, _, sig, _ = brand_signatures(spark, sf_dir)
    exact = mining.apriori(sig, P.cutoff(0.005, m.n_obs))
    return mining.recall(mining.sample_mine(sig, 0.5, m.n_obs, 0.005), exact)


def _patterns(key):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        m = f(spark, sf_dir)
        sig = P.cut(P.signatures(m.cells, P.top_variables(m.cells, 12)))
        found = mining.enumerate_patterns(sig, 12, P.cutoff(ms, m.n_obs))
        return D.contract(M.closed_collapse(found, sig))

    return run


for _key, (_, _ms) in WL.WORKLOADS.items():
    query(f"{_key}_patterns", V.patterns(V.VIEWS[_key], 12, _ms))(_patterns(_key))


WIDE = f"""WITH {V.W5}, c AS (SELECT item, count(*) AS s FROM it GROUP BY item HAVING count(*) / (SELECT n FROM n) > 0.055),
p AS (SELECT a.item AS x, b.item AS y, count(*) AS s FROM it a JOIN it b ON a.obs = b.obs AND a.item < b.item GROUP BY 1, 2 HAVING count(*) / (SELECT n FROM n) > 0.055),
t AS (SELECT p.x, p.y, c.item AS z, count(*) AS s FROM p JOIN it a ON a.item = p.x JOIN it b ON b.item = p.y AND a.obs = b.obs JOIN it c ON c.obs = a.obs AND c.item > p.y GROUP BY 1, 2, 3 HAVING count(*) / (SELECT n FROM n) > 0.055)
SELECT item AS pattern, 1 AS n_vars, s::BIGINT AS support FROM c WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.s = c.s AND item IN (x, y))
UNION ALL SELECT x || ',' || y, 2, s::BIGINT FROM p WHERE NOT EXISTS (SELECT 1 FROM t WHERE t.s = p.s AND p.x IN (t.x, t.y, t.z) AND p.y IN (t.x, t.y, t.z))
UNION ALL SELECT x || ',' || y || ',' || z, 3, s::BIGINT FROM t"""


@query("wide_patterns", WIDE)
def wide_patterns(spark, sf_dir):
    """All 128 variables of the embedding bins at once: more than a mask holds."""
    got = discover_wide(WL.embedding_bins(spark, sf_dir), 0.055)
    return got.select(F.array_join("items", ",").alias("pattern"), F.size("items").alias("n_vars"), F.col("support").cast("long").alias("support"))


@query("wide_discover", WIDE)
def wide_discover(spark, sf_dir):
    """The same through the entry point that takes any matrix: its profile asks for the wide form."""
    got = find(WL.embedding_bins(spark, sf_dir), 0.055, cap=6)
    return got.select(F.array_join("items", ",").alias("pattern"), F.size("items").alias("n_vars"), F.col("support").cast("long").alias("support"))


def _whole(key):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        return closed_by_length(f(spark, sf_dir), ms)

    return run


# Closed patterns by length: listed, those of w6 are thirty million rows on sf0.01. All variables at the stated minimum support; SQL would try all 2^k masks.
for _key in WL.WORKLOADS:
    query(f"{_key}_whole")(_whole(_key))


# Measures of local patterns before the merge, by strategy.
def measures_sql(view: str, min_sup: float) -> str:
    """Groups of all three strategies by recursion, local and global closed patterns by enumeration."""
    return f"""WITH RECURSIVE {view}, {V.top(8)}, cells AS (SELECT obs, v, 1 AS l FROM it JOIN vars USING (item)), {JOINT}, {SCORE}, {RANDOM},
sim AS (SELECT x.v::INT AS a, y.v::INT AS b, coalesce(purity * concentration, 0) AS s FROM vars x JOIN vars y ON x.v < y.v LEFT JOIN r ON r.a = x.v AND r.b = y.v),
st AS (SELECT 0 AS step, sign, list_transform(range(0, 8), lambda x: x::INT) AS c FROM (SELECT unnest([1, -1]) AS sign)
UNION ALL SELECT step + 1, sign, list_transform(c, lambda x: CASE WHEN x = v THEN u ELSE x END) FROM (
  SELECT step, sign, c, u, v FROM (
    SELECT step, sign, c, u, v, row_number() OVER (PARTITION BY sign ORDER BY sign * round(s, 9) DESC, u, v) AS k FROM (
      SELECT step, sign, c, least(c[a + 1], c[b + 1]) AS u, greatest(c[a + 1], c[b + 1]) AS v, avg(s) AS s FROM st, sim WHERE c[a + 1] <> c[b + 1] GROUP BY ALL)
    WHERE len(list_filter(c, lambda x: x = u OR x = v)) <= 4) WHERE k = 1)),
fin AS (SELECT sign, c FROM (SELECT *, row_number() OVER (PARTITION BY sign ORDER BY step DESC) AS k FROM st) WHERE k = 1),
home AS (SELECT CASE WHEN sign = 1 THEN 'similar' ELSE 'dissimilar' END AS strategy, i AS v, c[i + 1] AS c FROM fin, (SELECT unnest(range(0, 8)) AS i) UNION ALL SELECT 'random', v, c FROM rc),
own AS (SELECT strategy, c, sum(1::BIGINT << v::INT)::BIGINT AS own FROM home GROUP BY 1, 2), {V.frequent(8, min_sup)}, {V.CLOSED},
f AS (SELECT strategy, c, mask, support FROM freq JOIN own ON (mask & own) = mask),
loc AS (SELECT strategy, avg(support) AS s, avg(bit_count(mask)) AS l, count(*) AS n FROM f x WHERE NOT EXISTS (SELECT 1 FROM f y WHERE y.strategy = x.strategy AND y.c = x.c AND y.support = x.support AND x.mask <> y.mask AND (x.mask & y.mask) = x.mask) GROUP BY 1)
SELECT 8 AS n_vars, 0 AS run, strategy, metric, round(CASE metric WHEN 'mean_support' THEN s WHEN 'mean_length' THEN l WHEN 'local_patterns' THEN n WHEN 'patterns' THEN (SELECT count(*) FROM closed) ELSE 255 END::DOUBLE, 6) AS value
FROM loc, (SELECT unnest(['mean_support', 'mean_length', 'local_patterns', 'patterns', 'bound']) AS metric)"""


def _measures(key):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        m = f(spark, sf_dir)
        m = WL.Matrix(m.cells.persist(), m.n_obs)
        rows = []
        for strategy in D.STRATEGIES:
            found = D.discover(m, P.top_variables(m.cells, 8), ms, strategy=strategy)
            local_ = found.local.agg(F.avg("support").alias("s"), F.avg(F.bit_count("mask")).alias("v"), F.count(F.lit(1)).alias("n")).first()
            rows += [(8, 0, strategy, k, round(float(v), 6)) for k, v in (("mean_support", local_["s"]), ("mean_length", local_["v"]), ("local_patterns", local_["n"]), ("patterns", found.patterns.count()), ("bound", 255))]
        m.cells.unpersist()
        return spark.createDataFrame(rows, "n_vars int, run int, strategy string, metric string, value double")

    return run


for _key, (_, _ms) in WL.WORKLOADS.items():
    query(f"{_key}_measures", measures_sql(V.VIEWS[_key], _ms))(_measures(_key))


def _whole_measures(key):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        m = f(spark, sf_dir)
        m = P.distinct_rows(m)
        variables = P.cut(P.numbered(m.cells.select("item").distinct()))
        n, rows = variables.count(), []
        total = number_of_closed(m, ms)
        for strategy in D.STRATEGIES:
            placed = P.cut(placed_variables(m, variables, 4, strategy))
            local_ = closed_local(weighted_rows(m, placed), P.cutoff(ms, m.n_obs)).agg(F.avg("support").alias("s"), F.avg(F.bit_count("p")).alias("v"), F.count(F.lit(1)).alias("n")).first()
            rows += [(n, 0, strategy, k, round(float(v), 6)) for k, v in (("mean_support", local_["s"]), ("mean_length", local_["v"]), ("local_patterns", local_["n"]), ("patterns", total)) if v is not None]
        return spark.createDataFrame(rows, "n_vars int, run int, strategy string, metric string, value double")

    return run


for _key in WL.WORKLOADS:
    query(f"{_key}_whole_measures")(_whole_measures(_key))

LOCAL_8 = f"""WITH {V.BRANDS}, {V.top(8)}, {RANDOM}, own AS (SELECT c, sum(1::BIGINT << v::INT)::BIGINT AS own FROM rc GROUP BY c), {V.frequent(8, MS)},
f AS (SELECT c, mask, support FROM freq JOIN own ON (mask & own) = mask),
loc AS (SELECT * FROM f a WHERE NOT EXISTS (SELECT 1 FROM f b WHERE b.c = a.c AND b.support = a.support AND a.mask <> b.mask AND (a.mask & b.mask) = a.mask)), {V.CLOSED}"""


def _random8(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    return D.discover(m, P.top_variables(m.cells, 8), MS, strategy="random")


def _measure(name, sql, value):
    @query(name, f"{LOCAL_8} {sql}")
    def run(spark, sf_dir):
        return value(_random8(spark, sf_dir))


HEAD = "SELECT 8 AS n_vars, 0 AS run, 'random' AS strategy, "
_head = lambda df, v: df.agg(v.alias("value")).select(F.lit(8).alias("n_vars"), F.lit(0).alias("run"), F.lit("random").alias("strategy"), F.round("value", 6).alias("value"))
_measure("measure_mean_support", HEAD + "round(avg(support), 6) AS value FROM loc", lambda d: _head(d.local, F.avg("support")))
_measure("measure_mean_length", HEAD + "round(avg(bit_count(mask)), 6) AS value FROM loc", lambda d: _head(d.local, F.avg(F.bit_count("mask"))))
_measure("measure_pattern_counts", HEAD + "count(*)::DOUBLE AS value FROM closed", lambda d: _head(d.patterns, F.count(F.lit(1)).cast("double")))
_measure("extension_rate", "SELECT round(1 - count(*) FILTER (WHERE mask IN (SELECT mask FROM closed)) / count(*), 6) AS rate FROM loc", lambda d: X.extension_rate(d.local, d.patterns).select(F.round("rate", 6).alias("rate")))
_measure("merge_work_counters", """, g AS (SELECT c, count(*) AS k, row_number() OVER (ORDER BY c) AS i FROM loc GROUP BY c) SELECT (SELECT max(k) FILTER (WHERE i = 1) * max(k) FILTER (WHERE i = 2) FROM g)::BIGINT AS compared, (SELECT count(DISTINCT a.mask | b.mask) FROM loc a JOIN loc b ON a.c < b.c JOIN freq ON freq.mask = (a.mask | b.mask))::BIGINT AS kept""",
         lambda d: d.patterns.sparkSession.createDataFrame([(d.measures["compared"], d.measures["kept"])], "compared long, kept long"))


@query("measure_pattern_bound", f"""WITH {V.W7}, f AS (SELECT row_number() OVER (ORDER BY count(*) DESC, item) AS k, count(*) / (SELECT n FROM n) > {WL.WORKLOADS['w7'][1]}::DOUBLE AS ok FROM it GROUP BY item)
SELECT s::INT AS n_vars, (pow(2, count(*) FILTER (WHERE ok AND k <= s)) - 1)::BIGINT AS bound FROM (SELECT unnest([4, 8, 12, 16, 20]) AS s) LEFT JOIN f ON true GROUP BY s""")
def measure_pattern_bound(spark, sf_dir):
    """Most patterns that the n most frequent variables of W-7 can have: infrequent ones are in none."""
    f, ms = WL.WORKLOADS["w7"]
    m = f(spark, sf_dir)
    frequent = mining.frequent_items(m.cells, P.cutoff(ms, m.n_obs)).agg(F.count(F.lit(1)).alias("k"))
    sizes = spark.createDataFrame([(s,) for s in X.SIZES], "n_vars int")
    return sizes.crossJoin(frequent).select("n_vars", (F.pow(F.lit(2.0), F.least("n_vars", "k")) - 1).cast("long").alias("bound"))


#: Draws that SQL checks by trying all masks; the whole experiment goes to 20 variables.
CHECKED = (4, 8, 12)


def draws_sql(view: str, min_sup: float, sizes=CHECKED, runs: int = X.RUNS, seed: int = 42) -> str:
    """vars, sig, freq and closed of all draws, by (k, run); variables numbered by name."""
    return f"""{view}, draws AS (SELECT k, run FROM (SELECT unnest({list(sizes)}) AS k), (SELECT unnest(range(0, {runs}))::INT AS run)),
ranked AS (SELECT run, item, row_number() OVER (PARTITION BY run ORDER BY md5('{seed}:' || run || ':' || item), item) AS r FROM (SELECT DISTINCT item FROM it), (SELECT DISTINCT run FROM draws)),
vars AS (SELECT k, run, item, row_number() OVER (PARTITION BY k, run ORDER BY item) - 1 AS v FROM ranked JOIN draws USING (run) WHERE r <= k),
sig AS (SELECT k, run, mask, count(*) AS w FROM (SELECT k, run, obs, sum(1::BIGINT << v::INT)::BIGINT AS mask FROM it JOIN vars USING (item) GROUP BY ALL) GROUP BY ALL),
freq AS (SELECT k, run, p AS mask, sum(w)::BIGINT AS support FROM sig JOIN (SELECT DISTINCT k, unnest(range(1, 1 << k::INT)) AS p FROM draws) USING (k) WHERE (mask & p) = p GROUP BY ALL HAVING sum(w) / (SELECT n FROM n) > {min_sup}::DOUBLE),
closed AS (SELECT * FROM freq a WHERE NOT EXISTS (SELECT 1 FROM freq b WHERE b.k = a.k AND b.run = a.run AND b.support = a.support AND b.mask <> a.mask AND (a.mask & b.mask) = a.mask)),
n_closed AS (SELECT k, run, count(c.mask) AS c FROM draws LEFT JOIN closed c USING (k, run) GROUP BY k, run)"""


@query("experiment_counts", f"""WITH {draws_sql(V.W7, 0.01)} SELECT k::INT AS n_vars, run, strategy, c::DOUBLE AS value FROM n_closed, (SELECT unnest(['similar', 'dissimilar', 'random']) AS strategy)""")
def experiment_counts(spark, sf_dir):
    """Closed patterns of every draw under every strategy: grouping never changes them."""
    runs = X.run_experiment("w7", WL.user_event_hours(spark, sf_dir), 0.01, CHECKED)
    return runs.where("metric = 'patterns'").select("n_vars", "run", "strategy", "value")


def _table2(key):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        got = X.pattern_counts(X.run_experiment(key, f(spark, sf_dir), ms, CHECKED))
        return got.select("dataset", "n_vars", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"), F.col("bound").cast("long").alias("bound"))

    return run


def series_sql(key: str, min_sup: float, sizes=CHECKED, cap: int = 4) -> str:
    """Mean support and length of closed local patterns by strategy; groups by recursion over all draws at once."""
    return f"""WITH RECURSIVE {draws_sql(V.VIEWS[key], min_sup, sizes)},
one AS (SELECT k, run, v, sum(w) AS c FROM sig JOIN vars USING (k, run) WHERE (mask >> v::INT) & 1 = 1 GROUP BY ALL),
pair AS (SELECT x.k, x.run, x.v::INT AS a, y.v::INT AS b, x.c AS ca, y.c AS cb FROM one x JOIN one y ON x.k = y.k AND x.run = y.run AND x.v < y.v),
met AS (SELECT p.k, p.run, a, b, ca, cb, sum(w)::DOUBLE AS c FROM pair p JOIN sig s ON s.k = p.k AND s.run = p.run AND (mask >> a) & 1 = 1 AND (mask >> b) & 1 = 1 GROUP BY ALL),
sim AS (SELECT p.k, p.run, p.a, p.b, coalesce(c / greatest(p.ca, p.cb) * (1 + c / n * ln(c / n) / ln(n)), 0) AS s FROM pair p LEFT JOIN met m ON m.k = p.k AND m.run = p.run AND m.a = p.a AND m.b = p.b, n),
st AS (SELECT 0 AS step, k, run, sign, list_transform(range(0, k), lambda x: x::INT) AS c FROM draws, (SELECT unnest([1, -1]) AS sign)
UNION ALL SELECT step + 1, k, run, sign, list_transform(c, lambda x: CASE WHEN x = v THEN u ELSE x END) FROM (
  SELECT *, row_number() OVER (PARTITION BY k, run, sign ORDER BY sign * round(s, 9) DESC, u, v) AS place FROM (
    SELECT step, st.k, st.run, sign, c, least(c[a + 1], c[b + 1]) AS u, greatest(c[a + 1], c[b + 1]) AS v, avg(s) AS s FROM st JOIN sim ON sim.k = st.k AND sim.run = st.run WHERE c[a + 1] <> c[b + 1] GROUP BY ALL)
  WHERE len(list_filter(c, lambda x: x = u OR x = v)) <= {cap}) WHERE place = 1),
fin AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY k, run, sign ORDER BY step DESC) AS last FROM st) WHERE last = 1),
rnd AS (SELECT k, run, v, floor((row_number() OVER (PARTITION BY k, run ORDER BY md5('42:' || item), item) - 1) / {cap}) AS g FROM vars),
home AS (SELECT CASE WHEN sign = 1 THEN 'similar' ELSE 'dissimilar' END AS strategy, k, run, i AS v, c[i + 1] AS g FROM fin, LATERAL (SELECT unnest(range(0, k)) AS i) UNION ALL SELECT 'random', k, run, v, g::INT FROM rnd),
own AS (SELECT strategy, k, run, g, sum(1::BIGINT << v::INT)::BIGINT AS own FROM home GROUP BY ALL),
f AS (SELECT strategy, freq.k, freq.run, g, mask, support FROM freq JOIN own ON own.k = freq.k AND own.run = freq.run AND (mask & own) = mask),
loc AS (SELECT strategy, k, run, avg(support) AS s, avg(bit_count(mask)) AS l FROM f x WHERE NOT EXISTS (SELECT 1 FROM f y WHERE y.strategy = x.strategy AND y.k = x.k AND y.run = x.run AND y.g = x.g AND y.support = x.support AND x.mask <> y.mask AND (x.mask & y.mask) = x.mask) GROUP BY ALL)
SELECT '{key}' AS dataset, metric, strategy, k::INT AS n_vars, round(avg(CASE metric WHEN 'mean_support' THEN s ELSE l END), 6) AS mean, round(stddev_samp(CASE metric WHEN 'mean_support' THEN s ELSE l END), 6) AS sd
FROM loc, (SELECT unnest(['mean_support', 'mean_length']) AS metric) GROUP BY ALL"""


def _series(key, sizes=CHECKED):
    f, ms = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        got = X.series(X.run_experiment(key, f(spark, sf_dir), ms, sizes)).where("metric in ('mean_support', 'mean_length')")
        return got.select("dataset", "metric", "strategy", "n_vars", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"))

    return run


for _key, (_, _ms) in WL.WORKLOADS.items():
    query(f"{_key}_table2", f"""WITH {draws_sql(V.VIEWS[_key], _ms)} SELECT '{_key}' AS dataset, k::INT AS n_vars, round(avg(c), 6) AS mean, round(stddev_samp(c), 6) AS sd, (pow(2, k) - 1)::BIGINT AS bound FROM n_closed GROUP BY k""")(_table2(_key))
    query(f"{_key}_series", series_sql(_key, _ms))(_series(_key))


def whole_experiment(spark, sf_dir, keys=tuple(WL.WORKLOADS)):
    """Every size and draw of the experiment on each workload, at its own minimum support."""
    runs = [X.run_experiment(k, f(spark, sf_dir), ms) for k, (f, ms) in WL.WORKLOADS.items() if k in keys]
    return M.union(runs)


for _key in WL.WORKLOADS:
    query(f"experiment_{_key}")(lambda spark, sf_dir, key=_key: whole_experiment(spark, sf_dir, (key,)))


@query("table2_layout")
def table2_layout(spark, sf_dir):
    return X.pattern_counts(whole_experiment(spark, sf_dir))


@query("figure5_series")
def figure5_series(spark, sf_dir):
    return X.series(whole_experiment(spark, sf_dir))


@query("table3_layout")
def table3_layout(spark, sf_dir):
    """Draws of size 20 are left out where the workload has just 20 variables: all ten are one."""
    runs = whole_experiment(spark, sf_dir)
    return X.time_tests(runs.where("n_vars <> 20 or dataset not in ('w4', 'w7')"))


# Significance
PVALUE = f"""WITH {V.BRANDS}, {V.top(8)}, {V.frequent(8, 0.02)}, s AS (SELECT v, sum(w) / (SELECT n FROM n) AS p FROM vars JOIN sig ON (mask >> v::INT) & 1 = 1 GROUP BY v),
q AS (SELECT mask, support, n, exp(sum(ln(p))) AS p FROM freq, s, n WHERE (mask >> v::INT) & 1 = 1 AND bit_count(mask) > 1 GROUP BY mask, support, n),
t AS (SELECT mask, support, sum(exp(lgamma(n + 1) - lgamma(k + 1.0) - lgamma(n - k + 1.0) + k * ln(p) + (n - k) * ln(1 - p))) AS pv FROM (SELECT *, unnest(range(support, n::BIGINT + 1)) AS k FROM q) GROUP BY mask, support)"""


def tested(spark, sf_dir):
    m, _, sig, _ = brand_signatures(spark, sf_dir, 8)
    found = mining.enumerate_patterns(sig, 8, P.cutoff(0.02, m.n_obs))
    one = {r["mask"]: r["support"] / m.n_obs for r in found.where("bit_count(mask) = 1").collect()}
    logs = F.array(*[F.log(F.lit(one.get(1 << i, 1.0))) for i in range(8)])
    p = F.exp(F.aggregate(P.bits("mask"), F.lit(0.0), lambda a, i: a + F.get(logs, i)))
    many = found.where("bit_count(mask) > 1").withColumn("p", p)
    return G.pattern_pvalue(many, m.n_obs, F.col("p"))


@query("pattern_pvalues", f"{PVALUE} SELECT {V.text(k=8)} AS pattern, support, round(least(pv, 1), 6) AS p_value FROM t")
def pattern_pvalues(spark, sf_dir):
    return tested(spark, sf_dir).select(P.as_text().alias("pattern"), F.col("support").cast("long").alias("support"), F.round("p_value", 6).alias("p_value"))


@query("pvalues_holm", f"""{PVALUE}, r AS (SELECT mask, least(pv, 1) AS pv, row_number() OVER (ORDER BY least(pv, 1), mask) AS k, count(*) OVER () AS m FROM t)
SELECT {V.text(k=8)} AS pattern, round(least(1, max((m - k + 1) * pv) OVER (ORDER BY k)), 6) AS holm, round(least(1, m * pv), 6) AS bonferroni FROM r""")
def pvalues_holm(spark, sf_dir):
    got = G.holm(tested(spark, sf_dir).select("mask", "p_value"))
    return got.select(P.as_text().alias("pattern"), F.round("holm", 6).alias("holm"), F.round("bonferroni", 6).alias("bonferroni"))


#: Attributes laid out as one item a level, like the published sets: an observation holds one of them, the others are missing.
ATTRIBUTES = [("part", "p_brand"), ("lineitem", "l_linestatus"), ("orders", "o_orderpriority"), ("customer", "c_nationkey"), ("events", "event_type")]


def _cut_sql(rows: str) -> str:
    """``rows``: dataset, n, q (the chance of an item)."""
    return f"""WITH d AS ({rows}), s AS (SELECT dataset, n::DOUBLE AS n, pow(q, 4) AS p FROM d),
u AS (SELECT dataset, k, exp(lgamma(n + 1) - lgamma(k + 1.0) - lgamma(n - k + 1.0) + k * ln(p) + (n - k) * ln(1 - p)) AS f FROM (SELECT *, unnest(range(0, n::BIGINT + 1)) AS k FROM s)),
v AS (SELECT dataset, k, sum(f) OVER (PARTITION BY dataset ORDER BY k DESC ROWS UNBOUNDED PRECEDING) AS tail FROM u)
SELECT dataset, min(k)::BIGINT AS min_support FROM v WHERE tail <= 0.05 GROUP BY dataset"""


@query("min_support_table1", _cut_sql(" UNION ALL ".join(f"SELECT '{c}' AS dataset, count(*) AS n, (100 - floor(100 * (1 - count({c}) / (count(*) * count(DISTINCT {c}))) + 0.5)) / 100 AS q FROM {t}" for t, c in ATTRIBUTES)))
def min_support_table1(spark, sf_dir):
    """Least significant support of four items from rows and missing cells in whole percent, as the published table has them."""
    out = []
    for t, c in ATTRIBUTES:
        got = load(spark, sf_dir, t).agg(F.count(F.lit(1)).alias("n"), F.count(c).alias("cells"), F.count_distinct(c).alias("m")).first()
        missing = math.floor(100 * (1 - got["cells"] / (got["n"] * got["m"])) + 0.5) if got["cells"] else 100
        out.append((c, G.min_support(got["n"], (100 - missing) / 100)))
    return spark.createDataFrame(out, "dataset string, min_support long")


@query("min_support_variants", _cut_sql(f"""SELECT dataset, (SELECT count(*) FROM orders) AS n, q FROM (WITH {V.BRANDS} SELECT 'density' AS dataset, count(*) / (SELECT n FROM n) / count(DISTINCT item) AS q FROM it
UNION ALL SELECT 'half', 1 / count(DISTINCT l_linestatus) FROM lineitem UNION ALL SELECT 'fifth', 1 / count(DISTINCT o_orderpriority) FROM orders)"""))
def min_support_variants(spark, sf_dir):
    """The chance of an item from the density of brands in orders, or one over the levels of an attribute (two, five)."""
    m = WL.brands(spark, sf_dir)
    levels = lambda t, c: load(spark, sf_dir, t).agg(F.count_distinct(c).alias("m")).first()["m"]
    chances = [("density", G.item_probability(m.cells, m.n_obs)), ("half", 1 / levels("lineitem", "l_linestatus")), ("fifth", 1 / levels("orders", "o_orderpriority"))]
    return spark.createDataFrame([(d, G.min_support(m.n_obs, q)) for d, q in chances], "dataset string, min_support long")


def _density_sql(key: str) -> str:
    """The share of present cells of a workload as the chance of every item, and the least significant count."""
    return f"""(SELECT dataset, min_support FROM (WITH {V.VIEWS[key]}, d AS (SELECT '{key}' AS dataset, n, (SELECT count(*) FROM it) / n / (SELECT count(DISTINCT item) FROM it) AS q FROM n), s AS (SELECT dataset, n, pow(q, 4) AS p FROM d),
u AS (SELECT dataset, k, exp(lgamma(n + 1) - lgamma(k + 1.0) - lgamma(n - k + 1.0) + k * ln(p) + (n - k) * ln(1 - p)) AS f FROM (SELECT *, unnest(range(0, n::BIGINT + 1)) AS k FROM s)),
v AS (SELECT dataset, k, sum(f) OVER (ORDER BY k DESC ROWS UNBOUNDED PRECEDING) AS tail FROM u)
SELECT dataset, min(k)::BIGINT AS min_support FROM v WHERE tail <= 0.05 GROUP BY dataset))"""


@query("min_support_density", " UNION ALL ".join(map(_density_sql, WL.WORKLOADS)))
def min_support_density(spark, sf_dir):
    """Least significant support of four items, the chance of an item taken from each workload's density."""
    out = []
    for key, (f, _) in WL.WORKLOADS.items():
        m = f(spark, sf_dir)
        out.append((key, G.min_support(m.n_obs, G.item_probability(m.cells, m.n_obs))))
    return spark.createDataFrame(out, "dataset string, min_support long")


# Paired tests: quantity against ten times the discount, of the first lines by supplier group.
TTEST = """WITH r AS (SELECT c_nationkey % 5 AS g, c_nationkey, avg(c_acctbal) AS x FROM customer GROUP BY ALL), q AS (SELECT s_nationkey, avg(s_acctbal) AS y FROM supplier GROUP BY ALL),
d AS (SELECT g, x - y AS d FROM r JOIN q ON c_nationkey = s_nationkey), s AS (SELECT g, avg(d) / (stddev_samp(d) / sqrt(count(*))) AS t, (count(*) - 1)::INT AS df FROM d GROUP BY g HAVING count(*) = 5),
a AS (SELECT *, atan(t / sqrt(df)) AS h FROM s), c AS (SELECT *, 0.5 + sin(h) * (1 + cos(h) * cos(h) / 2) / 2 AS p FROM a)
SELECT g::STRING AS pair, round(t, 6) AS t, df, round(p, 6) AS p_less, round(1 - p, 6) AS p_greater FROM c"""


def _ttest(spark, sf_dir):
    from vpatterns.sources.tables import load

    x = load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.avg("c_acctbal").alias("x"))
    y = load(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.avg("s_acctbal").alias("y"))
    rows = x.join(y, F.col("c_nationkey") == F.col("s_nationkey")).withColumn("pair", (F.col("c_nationkey") % 5).cast("string"))
    got = G.paired_ttest(rows, "x", "y", ["pair"]).where("df = 4")
    return got.select("pair", F.round("t", 6).alias("t"), "df", F.round("p_less", 6).alias("p_less"), F.round("p_greater", 6).alias("p_greater"))


query("ttest_less", TTEST.replace(", round(1 - p, 6) AS p_greater", ""))(lambda spark, sf_dir: _ttest(spark, sf_dir).drop("p_greater"))
query("ttest_greater", TTEST.replace(", round(p, 6) AS p_less", ""))(lambda spark, sf_dir: _ttest(spark, sf_dir).drop("p_less"))


@query("ttest_independent")
def ttest_independent(spark, sf_dir):
    from vpatterns.sources.tables import load

    return G.independent_ttest(load(spark, sf_dir, "customer"), "c_acctbal", "c_mktsegment", "BUILDING", "MACHINERY")


# Other coherences, on planted numbers
PLANT = """e AS (SELECT vec_id AS obs, list_transform(embedding[1:20], lambda v: floor(v::DOUBLE / 0.01::DOUBLE)::BIGINT) AS g FROM embeddings),
o AS (SELECT *, list_sort(g[11:15]) AS s, obs % 4 AS k FROM e),
val AS (SELECT obs, i AS var, CASE
WHEN i <= 5 THEN CASE WHEN k = 0 THEN g[1] + [0, 1, 3, -2, 2][i] ELSE g[i] END
WHEN i <= 10 THEN CASE WHEN k = 1 THEN [2, 4, 8, 1, 6][i - 5] * (abs(g[6]) % 7 + 1) ELSE g[i] END
WHEN i <= 15 THEN CASE WHEN k = 2 THEN s[i - 10] * 10 + (i - 10) ELSE g[i] * 10 END
ELSE CASE WHEN k = 3 THEN [7, -3, 0, 12, 5][i - 15] ELSE g[i] END END AS x FROM o, (SELECT unnest(range(1, 21)) AS i)),
n AS (SELECT count(*)::DOUBLE AS n FROM embeddings)"""


def planted(spark, sf_dir, first, last):
    values = WL.planted_numeric(spark, sf_dir).where(f"var between {first} and {last}")
    return values, P.cutoff(0.1, values.select("obs").distinct().count())


@query("planted_values", f"WITH {PLANT} SELECT obs, var::INT AS var, x::BIGINT AS value FROM val")
def planted_values(spark, sf_dir):
    return WL.planted_numeric(spark, sf_dir)


@query("additive_pairs", f"WITH {PLANT} SELECT a.var::INT AS pivot, b.var::INT AS var, (b.x - a.x)::DOUBLE AS d, count(*)::BIGINT AS support FROM val a JOIN val b ON a.obs = b.obs AND a.var < b.var WHERE b.var <= 5 GROUP BY ALL")
def additive_pairs(spark, sf_dir):
    return H.pivot_differences(planted(spark, sf_dir, 1, 5)[0]).groupBy("pivot", "var", "d").agg(F.count(F.lit(1)).alias("support"))


@query("multiplicative_pairs", f"WITH {PLANT} SELECT a.var::INT AS pivot, b.var::INT AS var, round(b.x / a.x, 9) AS d, count(*)::BIGINT AS support FROM val a JOIN val b ON a.obs = b.obs AND a.var < b.var WHERE a.var BETWEEN 6 AND 10 AND b.var <= 10 AND a.x <> 0 AND b.x <> 0 GROUP BY ALL")
def multiplicative_pairs(spark, sf_dir):
    return H.pivot_differences(planted(spark, sf_dir, 6, 10)[0], "multiplicative").groupBy("pivot", "var", "d").agg(F.count(F.lit(1)).alias("support"))


def _offset_sql(first: int, combine: str, where: str = "") -> str:
    """Each set of variables, its rows grouped by all differences to the first of them."""
    return f"""WITH {PLANT}, m AS (SELECT p, list_filter(range(0, 5), lambda i: (p >> i::INT) & 1 = 1) AS vs FROM (SELECT unnest(range(1, 32)) AS p)),
w AS (SELECT obs, list(x ORDER BY var) AS l FROM val WHERE var BETWEEN {first} AND {first + 4} GROUP BY obs),
r AS (SELECT list_transform(vs, lambda i: i + {first}) AS vars, list_transform(vs, lambda i: {combine}) AS offs FROM w, m WHERE len(vs) > 1 {where}),
f AS (SELECT vars, offs, count(*)::BIGINT AS support FROM r GROUP BY ALL HAVING count(*) / (SELECT n FROM n) > 0.1)
SELECT array_to_string(vars, ',') AS pattern, array_to_string(list_transform(offs, lambda o: round(o, 3)::VARCHAR), ',') AS offsets, support FROM f"""


def _offsets(first, kind):
    def run(spark, sf_dir):
        values, least = planted(spark, sf_dir, first, first + 4)
        got = H.mine_offsets(values, least, kind)
        text = lambda c, f: F.array_join(F.transform(c, f), ",")
        return got.select(text("vars", lambda v: v.cast("string")).alias("pattern"), text("offsets", lambda o: F.round(o, 3).cast("string")).alias("offsets"), "support")

    return run


query("mine_additive_planted", _offset_sql(1, "(l[i + 1] - l[vs[1] + 1])::DOUBLE"))(_offsets(1, "additive"))
query("mine_multiplicative_planted", _offset_sql(6, "round(l[i + 1] / l[vs[1] + 1], 9)", "AND len(list_filter(vs, lambda i: l[i + 1] = 0)) = 0"))(_offsets(6, "multiplicative"))

ORDER = f"""WITH {PLANT}, v AS (SELECT obs, var, x FROM val WHERE var BETWEEN 11 AND 14),
two AS (SELECT a.obs, [a.var, b.var] AS s, b.x FROM v a JOIN v b ON a.obs = b.obs AND a.x < b.x),
three AS (SELECT two.obs, list_append(s, v.var) AS s, v.x FROM two JOIN v ON two.obs = v.obs AND two.x < v.x),
four AS (SELECT three.obs, list_append(s, v.var) AS s, v.x FROM three JOIN v ON three.obs = v.obs AND three.x < v.x),
every AS (SELECT s FROM two UNION ALL SELECT s FROM three UNION ALL SELECT s FROM four)
SELECT array_to_string(s, ',') AS pattern, count(*)::BIGINT AS support FROM every GROUP BY s HAVING count(*) / (SELECT n FROM n) > 0.1"""


def _seq(df):
    return df.select(F.array_join(F.transform("seq", lambda v: v.cast("string")), ",").alias("pattern"), F.col("support").cast("long").alias("support"))


@query("mine_order_planted", ORDER)
def mine_order_planted(spark, sf_dir):
    values, least = planted(spark, sf_dir, 11, 14)
    return _seq(H.mine_order(values, least))


@query("prefixspan_order_planted", ORDER)
def prefixspan_order_planted(spark, sf_dir):
    values, least = planted(spark, sf_dir, 11, 14)
    return _seq(H.prefixspan(values, least, values.select("obs").distinct().count()))


@query("order_sequences", f"WITH {PLANT}, t AS (SELECT obs, x, array_to_string(list(var ORDER BY var), '=') AS s FROM val WHERE var <= 5 GROUP BY obs, x) SELECT obs, string_agg(s, '<' ORDER BY x) AS sequence FROM t GROUP BY obs")
def order_sequences(spark, sf_dir):
    got = H.order_sequences(planted(spark, sf_dir, 1, 5)[0])
    return got.select("obs", F.array_join(F.transform("sequence", lambda s: F.array_join(F.transform(s, lambda v: v.cast("string")), "=")), "<").alias("sequence"))


@query("merge_additive_planted", _offset_sql(1, "(l[i + 1] - l[vs[1] + 1])::DOUBLE", "AND len(list_filter(vs, lambda i: i < 3)) > 0 AND len(list_filter(vs, lambda i: i >= 3)) > 0"))
def merge_additive_planted(spark, sf_dir):
    """Groups 1-3 and 4-5 mined apart, their rows split by the difference of pivots."""
    values, least = planted(spark, sf_dir, 1, 5)
    sides = []
    for a, b in ((1, 3), (4, 5)):
        own = values.where(f"var between {a} and {b}")
        sides.append(H.offset_rows(own, H.mine_offsets(own, least)))
    rows = H.merge_offset(sides[0], sides[1], least)
    got = rows.groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
    text = lambda c, f: F.array_join(F.transform(c, f), ",")
    return got.select(text("vars", lambda v: v.cast("string")).alias("pattern"), text("offsets", lambda o: F.round(o, 3).cast("string")).alias("offsets"), "support")


@query("merge_order_planted", ORDER.replace("FROM every GROUP", "FROM every WHERE len(list_filter(s, lambda i: i < 13)) > 0 AND len(list_filter(s, lambda i: i >= 13)) > 0 GROUP"))
def merge_order_planted(spark, sf_dir):
    values, least = planted(spark, sf_dir, 11, 14)
    sides = []
    for a, b in ((11, 12), (13, 14)):
        own = values.where(f"var between {a} and {b}")
        one = own.select(F.array("var").alias("seq")).distinct()
        sides.append(H.mine_order(own, least).select("seq").unionByName(one))
    return _seq(H.merge_order(sides[0], sides[1], values, least))


def _closed_sql(sql: str) -> str:
    """The patterns of ``_offset_sql`` that none of the same support encloses."""
    head, tail = sql.rsplit("\nSELECT", 1)
    shut = """, shut AS (SELECT * FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.support = f.support AND len(g.vars) > len(f.vars) AND list_has_all(g.vars, f.vars)
AND list_bool_and(list_transform(range(1, len(f.vars) + 1), lambda i: abs({rest}) < 1e-9))))"""
    at = lambda v: f"g.offs[list_position(g.vars, {v})]"
    rest = f"{at('f.vars[i]')} - {at('f.vars[1]')} - f.offs[i]" if "round(l[i + 1] /" not in sql else f"{at('f.vars[i]')} / {at('f.vars[1]')} / f.offs[i] - 1"
    return head + shut.replace("{rest}", rest) + "\nSELECT" + tail.replace("FROM f", "FROM shut")


def _pipeline_offsets(first, kind):
    def run(spark, sf_dir):
        values, _ = planted(spark, sf_dir, first, first + 4)
        got = discover_kind(values, values.select("obs").distinct().count(), 0.1, kind, cap=3)
        text = lambda c, f: F.array_join(F.transform(c, f), ",")
        return got.select(text("vars", lambda v: v.cast("string")).alias("pattern"), text("offsets", lambda o: F.round(o, 3).cast("string")).alias("offsets"), F.col("support").cast("long").alias("support"))

    return run


query("pipeline_additive", _closed_sql(_offset_sql(1, "(l[i + 1] - l[vs[1] + 1])::DOUBLE")))(_pipeline_offsets(1, "additive"))
query("pipeline_multiplicative", _closed_sql(_offset_sql(6, "round(l[i + 1] / l[vs[1] + 1], 9)", "AND len(list_filter(vs, lambda i: l[i + 1] = 0)) = 0")))(_pipeline_offsets(6, "multiplicative"))


@query("pipeline_order", ORDER)
def pipeline_order(spark, sf_dir):
    values, _ = planted(spark, sf_dir, 11, 14)
    return _seq(discover_kind(values, values.select("obs").distinct().count(), 0.1, "order", cap=2))


@query("merge_multiplicative_planted", _offset_sql(6, "round(l[i + 1] / l[vs[1] + 1], 9)", "AND len(list_filter(vs, lambda i: l[i + 1] = 0)) = 0 AND len(list_filter(vs, lambda i: i < 3)) > 0 AND len(list_filter(vs, lambda i: i >= 3)) > 0"))
def merge_multiplicative_planted(spark, sf_dir):
    """Groups 6-8 and 9-10 mined apart, their rows split by the ratio of pivots."""
    values, least = planted(spark, sf_dir, 6, 10)
    sides = []
    for a, b in ((6, 8), (9, 10)):
        own = values.where(f"var between {a} and {b}")
        sides.append(H.offset_rows(own, H.mine_offsets(own, least, "multiplicative"), "multiplicative"))
    rows = H.merge_offset(sides[0], sides[1], least, "multiplicative")
    got = rows.groupBy("vars", "offsets").agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= least)
    text = lambda c, f: F.array_join(F.transform(c, f), ",")
    return got.select(text("vars", lambda v: v.cast("string")).alias("pattern"), text("offsets", lambda o: F.round(o, 3).cast("string")).alias("offsets"), "support")


_FIVE = ORDER.replace("BETWEEN 11 AND 14", "BETWEEN 11 AND 15").split("every AS")[0] + "five AS (SELECT four.obs, list_append(s, v.var) AS s, v.x FROM four JOIN v ON four.obs = v.obs AND four.x < v.x), "


def _recovery_sql() -> str:
    """Of each plant: rows by pattern, how many of them are the plant's, and the best overlap of cells."""
    each = []
    for plant, k, first, combine, where in (
        ("additive", 0, 1, "(l[i + 1] - l[vs[1] + 1])::DOUBLE", ""),
        ("multiplicative", 1, 6, "round(l[i + 1] / l[vs[1] + 1], 9)", "AND len(list_filter(vs, lambda i: l[i + 1] = 0)) = 0"),
        ("constant", 3, 16, "l[i + 1]::DOUBLE", ""),
    ):
        head = _offset_sql(first, combine, where).rsplit(",\nf AS", 1)[0].replace("SELECT list_transform(vs, lambda i: i +", "SELECT obs, list_transform(vs, lambda i: i +")
        each.append(f"(SELECT '{plant}' AS plant, best FROM ({head}, g AS (SELECT vars, offs, count(*) AS c, count(*) FILTER (WHERE obs % 4 = {k}) AS hit FROM r GROUP BY ALL HAVING count(*) / (SELECT n FROM n) > 0.1) SELECT round(max(hit * len(vars) / (c * len(vars) + 5 * (SELECT count(*) FROM embeddings WHERE vec_id % 4 = {k}) - hit * len(vars))::DOUBLE), 6) AS best FROM g))")
    every = "every AS (" + " UNION ALL ".join(f"SELECT obs, s FROM {x}" for x in ("two", "three", "four", "five")) + ")"
    each.append(f"(SELECT 'order' AS plant, best FROM ({_FIVE}{every}, g AS (SELECT s AS vars, count(*) AS c, count(*) FILTER (WHERE obs % 4 = 2) AS hit FROM every GROUP BY s HAVING count(*) / (SELECT n FROM n) > 0.1) SELECT round(max(hit * len(vars) / (c * len(vars) + 5 * (SELECT count(*) FROM embeddings WHERE vec_id % 4 = 2) - hit * len(vars))::DOUBLE), 6) AS best FROM g))")
    return " UNION ALL ".join(each)


@query("planted_recovery", _recovery_sql())
def planted_recovery(spark, sf_dir):
    """Overlap of each plant's cells with the best pattern found on its variables."""
    out = []
    for plant, k, first in (("additive", 0, 1), ("multiplicative", 1, 6), ("order", 2, 11), ("constant", 3, 16)):
        values, least = planted(spark, sf_dir, first, first + 4)
        own = values.select("obs").distinct().where(F.col("obs") % 4 == k)
        if plant == "order":
            rows, key = H.order_rows(values, H.mine_order(values, least)), ["seq"]
        elif plant == "constant":  # an observation of value 0 as pivot turns values into differences
            both = values.unionByName(values.select("obs", F.lit(0).alias("var"), F.lit(0).cast("long").alias("value")).distinct())
            found = H.mine_offsets(both, least).where("vars[0] = 0 and size(vars) > 2")
            rows = H.offset_rows(both, found).where("size(vars) > 2").select("obs", F.slice("vars", 2, 99).alias("vars"), "offsets")
            key = ["vars", "offsets"]
        else:
            rows = H.offset_rows(values, H.mine_offsets(values, least, plant), plant).where("size(vars) > 1")
            key = ["vars", "offsets"]
        out.append(X.cell_recovery(rows, key, own, list(range(first, first + 5)), plant))
    return M.union(out)
