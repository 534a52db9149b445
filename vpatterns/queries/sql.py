"""The SQL front end: table functions with partitions, functions of two columns."""

from __future__ import annotations

from pyspark.sql import functions as F

from vpatterns.functions.sqlapi import register
from vpatterns.operators import clustering
from vpatterns.operators import prepare as P
from vpatterns.operators import similarity as S
from vpatterns.queries import query
from vpatterns.queries import views as V
from vpatterns.queries.mine import K, PARTS_SQL, brand_signatures
from vpatterns.queries.similar import brand_cells, cluster_sql
from vpatterns.sources.tables import load


@query("udtf_frequent_patterns", f"{PARTS_SQL} SELECT cluster_id, {V.text(k=K)} AS pattern, support FROM loc")
def udtf_frequent_patterns(spark, sf_dir):
    register(spark)
    m, variables, sig, least = brand_signatures(spark, sf_dir)
    groups = clustering.random_clusters(variables, 4).groupBy("cluster_id").agg(F.bit_or(F.expr("shiftleft(1L, var_id)")).alias("own"))
    parts = sig.join(F.broadcast(groups)).select("cluster_id", F.expr("mask & own").alias("mask"), "w").where("mask <> 0").groupBy("cluster_id", "mask").agg(F.sum("w").alias("w"))
    got = None
    for c in sorted(r["cluster_id"] for r in groups.collect()):
        one = parts.where(F.col("cluster_id") == c).select("mask", "w")
        found = spark.sql(f"SELECT {c} AS cluster_id, mask, support FROM vp_frequent_patterns(TABLE({{t}}) WITH SINGLE PARTITION, {least})", t=one)
        got = found if got is None else got.unionByName(found)
    return got.select("cluster_id", P.as_text().alias("pattern"), "support")


@query("udtf_clusters", cluster_sql())
def udtf_clusters(spark, sf_dir):
    register(spark)
    m, _, cells = brand_cells(spark, sf_dir)
    sim = S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs).select("a", "b", "sim")
    return spark.sql("SELECT * FROM vp_clusters(TABLE({t}) WITH SINGLE PARTITION, 4)", t=sim)


@query("udaf_pattern_sim", """WITH c AS (SELECT l_suppkey, l_returnflag AS a, l_linestatus AS b FROM lineitem), n AS (SELECT l_suppkey, count(*)::DOUBLE AS n FROM c GROUP BY 1),
j AS (SELECT l_suppkey, a, b, count(*) AS c FROM c GROUP BY 1, 2, 3), m AS (SELECT *, sum(c) OVER (PARTITION BY l_suppkey, a) AS ca, sum(c) OVER (PARTITION BY l_suppkey, b) AS cb FROM j)
SELECT l_suppkey, round(avg(c / greatest(ca, cb)) * (1 + sum(c / n * ln(c / n)) / ln(min(n))), 6) AS sim FROM m JOIN n USING (l_suppkey) GROUP BY 1""")
def udaf_pattern_sim(spark, sf_dir):
    register(spark)
    line = load(spark, sf_dir, "lineitem").select("l_suppkey", "l_returnflag", "l_linestatus")
    return spark.sql("SELECT l_suppkey, round(vp_pattern_sim(l_returnflag, l_linestatus), 6) AS sim FROM {t} GROUP BY l_suppkey", t=line)


@query("udf_tails", """WITH x AS (SELECT c_mktsegment AS segment, n_regionkey, avg(c_acctbal) AS x FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL),
s AS (SELECT segment, (avg(x) - (SELECT avg(c_acctbal) FROM customer)) / (stddev_samp(x) / sqrt(count(*))) AS t FROM x GROUP BY segment HAVING count(*) = 5), a AS (SELECT *, atan(t / sqrt(4)) AS h FROM s)
SELECT segment, round(t, 6) AS t, round(0.5 + sin(h) * (1 + cos(h) * cos(h) / 2) / 2, 6) AS cdf FROM a""")
def udf_tails(spark, sf_dir):
    """A segment's mean balances in the five regions against the mean of all customers."""
    register(spark)
    customer, nation = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    means = customer.join(nation, customer.c_nationkey == nation.n_nationkey).groupBy(F.col("c_mktsegment").alias("segment"), "n_regionkey").agg(F.avg("c_acctbal").alias("x"))
    of_segment = means.groupBy("segment").agg(F.avg("x").alias("mean"), F.stddev_samp("x").alias("s"), F.count(F.lit(1)).alias("n")).where("n = 5")
    t = of_segment.crossJoin(customer.agg(F.avg("c_acctbal").alias("all"))).select("segment", F.expr("(mean - all) / (s / sqrt(n))").alias("t"))
    return spark.sql("SELECT segment, round(t, 6) AS t, round(vp_t_cdf(t, 4.0D), 6) AS cdf FROM {t}", t=t)
