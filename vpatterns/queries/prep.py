"""Preparation and coherence (D-, H- keys)."""

from __future__ import annotations

from pyspark.sql import functions as F

from vpatterns.functions import significance
from vpatterns.operators import coherence as H
from vpatterns.operators import prepare as P
from vpatterns.queries import query
from vpatterns.queries import views as V
from vpatterns.sources import workloads as WL
from vpatterns.sources.tables import load

NUMERIC = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
PARTS = "SELECT p_partkey, 'p_size' AS variable, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part"


def part_cells(spark, sf_dir):
    return P.to_cells(load(spark, sf_dir, "part"), "p_partkey", ["p_size", "p_retailprice"])


@query("cells_unpivot", PARTS)
def cells_unpivot(spark, sf_dir):
    return part_cells(spark, sf_dir)


@query("cells_pivot", "SELECT p_partkey, p_size::DOUBLE AS p_size, p_retailprice FROM part")
def cells_pivot(spark, sf_dir):
    return P.to_wide(part_cells(spark, sf_dir), "p_partkey", ["p_size", "p_retailprice"])


@query("embedding_cells", "SELECT vec_id, generate_subscripts(embedding, 1)::INT AS var_id, unnest(embedding)::DOUBLE AS value FROM embeddings")
def embedding_cells(spark, sf_dir):
    return P.explode_packed(load(spark, sf_dir, "embeddings"), "vec_id", "embedding")


@query("cells_transpose", "SELECT generate_subscripts(embedding, 1)::INT AS obs_id, vec_id AS var_id, unnest(embedding)::DOUBLE AS value FROM embeddings")
def cells_transpose(spark, sf_dir):
    cells = embedding_cells(spark, sf_dir).withColumnRenamed("vec_id", "obs_id")
    return P.transpose_cells(cells)


@query("presence_line_attributes", f"WITH {V.W3} SELECT item, count(*)::BIGINT AS n FROM it GROUP BY item")
def presence_line_attributes(spark, sf_dir):
    return WL.line_attributes(spark, sf_dir).cells.groupBy("item").agg(F.count(F.lit(1)).alias("n"))


@query("presence_columns", "SELECT obs, item FROM (SELECT c_custkey AS obs, unnest(['c_nationkey=' || c_nationkey, 'c_mktsegment=' || c_mktsegment]) AS item FROM customer) WHERE item IS NOT NULL")
def presence_columns(spark, sf_dir):
    return P.to_presence(load(spark, sf_dir, "customer"), "c_custkey", ["c_nationkey", "c_mktsegment"])


def _levels(df):
    return df.groupBy("variable", "level").agg(F.count(F.lit(1)).alias("n"))


@query("discretise_width", f"""WITH c AS ({PARTS}), e AS (SELECT variable, min(value) AS lo, max(value) AS hi FROM c GROUP BY variable)
SELECT variable, CASE WHEN hi = lo THEN 0 ELSE least(floor((value - lo) / (hi - lo) * 8), 7) END::INT AS level, count(*)::BIGINT AS n FROM c JOIN e USING (variable) GROUP BY 1, 2""")
def discretise_width(spark, sf_dir):
    return _levels(P.equal_width(part_cells(spark, sf_dir), 8))


@query("discretise_freq", f"""WITH c AS ({PARTS}), e AS (SELECT variable, quantile_cont(value, [0.25, 0.5, 0.75]) AS b FROM c GROUP BY variable)
SELECT variable, len(list_filter(b, lambda x: x <= value))::INT AS level, count(*)::BIGINT AS n FROM c JOIN e USING (variable) GROUP BY 1, 2""")
def discretise_freq(spark, sf_dir):
    return _levels(P.equal_frequency(part_cells(spark, sf_dir), 4))


@query("discretise_sign", f"WITH {V.W5} SELECT i::INT AS var_id, CASE WHEN v > 0 THEN 1 ELSE -1 END AS level, count(*)::BIGINT AS n FROM cell WHERE abs(v) > 0.1 GROUP BY 1, 2")
def discretise_sign(spark, sf_dir):
    return P.signs(embedding_cells(spark, sf_dir), 0.1).groupBy("var_id", "level").agg(F.count(F.lit(1)).alias("n"))


DRAW = "SELECT item, md5('42:' || run || ':' || item) AS h FROM (SELECT DISTINCT item FROM it)"


@query("variable_draws", f"WITH {V.BRANDS}, d AS (SELECT run, item, row_number() OVER (PARTITION BY run ORDER BY md5('42:' || run || ':' || item), item) AS r FROM (SELECT DISTINCT item FROM it), (SELECT unnest([0, 1, 2]) AS run)) SELECT run::INT AS run, item FROM d WHERE r <= 8")
def variable_draws(spark, sf_dir):
    items = WL.brands(spark, sf_dir).cells.select("item").distinct()
    out = [P.draw(items, 8, run).withColumn("run", F.lit(run)) for run in range(3)]
    return out[0].unionByName(out[1]).unionByName(out[2])


def _profile(key):
    f, _ = WL.WORKLOADS[key]

    def run(spark, sf_dir):
        m = f(spark, sf_dir)
        p = P.profile(m.cells, m.n_obs)
        density = p.first()["missing_pct"]
        least = significance.min_support(m.n_obs, 1 - density / 100)
        return p.withColumn("min_support", F.lit(least).cast("long"))

    return run


def profile_sql(view: str) -> str:
    """The support cut by the logarithm of the gamma function, summed from the top."""
    return f"""WITH {view}, p AS (SELECT (SELECT n FROM n) AS n, count(DISTINCT item) AS m, count(*) AS c FROM it),
q AS (SELECT n, m, round(100 * (1 - c / (n * m)), 6) AS missing FROM p), s AS (SELECT *, pow(1 - missing / 100, 4) AS pr FROM q),
t AS (SELECT unnest(range(0, n::BIGINT + 1)) AS k, n, pr FROM s),
u AS (SELECT k, exp(lgamma(n + 1) - lgamma(k + 1.0) - lgamma(n - k + 1.0) + k * ln(pr) + (n - k) * ln(1 - pr)) AS d FROM t),
v AS (SELECT k, sum(d) OVER (ORDER BY k DESC ROWS UNBOUNDED PRECEDING) AS tail FROM u)
SELECT n::BIGINT AS n_obs, m::BIGINT AS n_vars, missing AS missing_pct, coalesce((SELECT min(k) FROM v WHERE tail <= 0.05), n + 1)::BIGINT AS min_support FROM q"""


for _key in WL.WORKLOADS:
    query(f"{_key}_profile", profile_sql(V.VIEWS[_key]))(_profile(_key))

_ALL = "\nUNION ALL\n".join(f"SELECT '{k}' AS dataset, * FROM ({profile_sql(v)})" for k, v in V.VIEWS.items())


@query("table1_profile", _ALL)
def table1_profile(spark, sf_dir):
    out = None
    for key in WL.WORKLOADS:
        one = _profile(key)(spark, sf_dir).select(F.lit(key).alias("dataset"), "n_obs", "n_vars", "missing_pct", "min_support")
        out = one if out is None else out.unionByName(one)
    return out


@query("signature_masks", f"WITH {V.BRANDS}, {V.top(12)} SELECT mask, w::BIGINT AS w FROM sig")
def signature_masks(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    return P.signatures(m.cells, P.top_variables(m.cells, 12))


@query("pattern_cover", f"WITH {V.BRANDS}, {V.top(12)}, r AS (SELECT obs, sum(1::BIGINT << v::INT)::BIGINT AS mask FROM it JOIN vars USING (item) GROUP BY obs) SELECT p, obs FROM r, (SELECT unnest([3, 5, 9]) AS p) WHERE (mask & p) = p")
def pattern_cover(spark, sf_dir):
    m = WL.brands(spark, sf_dir)
    rows = P.row_masks(m.cells, P.top_variables(m.cells, 12))
    return P.cover(spark.createDataFrame([(3,), (5,), (9,)], "mask int"), rows).select(F.col("p").cast("int").alias("p"), "obs")


# Biclusters of the coherence keys: 8 groups of vectors over dimensions 1-4, with a row
# adjustment, a factor or an order made by expressions that both engines know.
CELLS = {
    "raw": "round(v, 3)",
    "overall": "CASE WHEN b < 4 THEN 2.5 ELSE v END",
    "constant": "CASE WHEN b < 4 THEN i * 1.5 ELSE v END",
    "additive": "CASE WHEN b < 4 THEN i * 1.5 + vec_id ELSE v END",
    "multiplicative": "CASE WHEN b < 4 THEN i * 1.5 * (vec_id + 1) ELSE abs(v) + 0.001 END",
    "order": "CASE WHEN b < 4 THEN i * 2 + vec_id % 2 ELSE v END",
}


def bicluster_sql(kind: str) -> str:
    return f"c AS (SELECT vec_id % 8 AS b, vec_id AS o, i, ({CELLS[kind]})::DOUBLE AS x FROM (SELECT vec_id, vec_id % 8 AS b, generate_subscripts(embedding, 1) AS i, unnest(embedding)::DOUBLE AS v FROM embeddings) WHERE i <= 4)"


def biclusters(spark, sf_dir, kind: str):
    cells = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 4)).alias("i", "v"))
    cells = cells.select("vec_id", (F.col("i") + 1).alias("i"), F.col("v").cast("double").alias("v"), (F.col("vec_id") % 8).alias("b"))
    return cells.select(F.col("b").alias("bicluster_id"), F.col("vec_id").alias("obs_id"), F.col("i").alias("var_id"), F.expr(CELLS[kind]).cast("double").alias("value"))


def _shown(df, digits=6):
    return df.select(F.col("bicluster_id").cast("int").alias("bicluster_id"), "holds", F.round("max_residual", digits).alias("max_residual"))


SHOW = "b::INT AS bicluster_id, holds, round(r, 6) AS max_residual"


@query("coherence_constant_overall", f"WITH {bicluster_sql('overall')}, s AS (SELECT b, max(x) - min(x) AS r FROM c GROUP BY b) SELECT b::INT AS bicluster_id, r <= 1e-9 AS holds, round(r, 6) AS max_residual FROM s")
def coherence_constant_overall(spark, sf_dir):
    return _shown(H.constant_overall(biclusters(spark, sf_dir, "overall")))


@query("coherence_constant", f"WITH {bicluster_sql('constant')}, s AS (SELECT b, max(r) AS r FROM (SELECT b, i, max(x) - min(x) AS r FROM c GROUP BY b, i) GROUP BY b) SELECT b::INT AS bicluster_id, r <= 1e-9 AS holds, round(r, 6) AS max_residual FROM s")
def coherence_constant(spark, sf_dir):
    return _shown(H.constant_on_variables(biclusters(spark, sf_dir, "constant")))


def _additive_sql(kind: str, value: str) -> str:
    return f"""WITH {bicluster_sql(kind)}, l AS (SELECT b, o, i, {value} AS x FROM c), r AS (SELECT b, o, avg(x) AS m FROM l GROUP BY b, o), k AS (SELECT b, i, avg(x) AS m FROM l GROUP BY b, i), g AS (SELECT b, avg(x) AS m FROM l GROUP BY b),
s AS (SELECT l.b, max(abs(x - r.m - k.m + g.m)) AS r FROM l JOIN r ON l.b = r.b AND l.o = r.o JOIN k ON l.b = k.b AND l.i = k.i JOIN g ON l.b = g.b GROUP BY l.b)
SELECT b::INT AS bicluster_id, r <= 1e-6 AS holds, round(r, 6) AS max_residual FROM s"""


@query("coherence_additive", _additive_sql("additive", "x"))
def coherence_additive(spark, sf_dir):
    return _shown(H.additive(biclusters(spark, sf_dir, "additive"), 1e-6))


@query("coherence_multiplicative", _additive_sql("multiplicative", "ln(x)"))
def coherence_multiplicative(spark, sf_dir):
    return _shown(H.multiplicative(biclusters(spark, sf_dir, "multiplicative"), 1e-6))


def _order_sql(line: str, item: str) -> str:
    return f"""WITH {bicluster_sql('order')}, m AS (SELECT b, {item} AS t, avg(x) AS m FROM c GROUP BY b, {item}),
s AS (SELECT c.b, lag(x) OVER (PARTITION BY c.b, {line} ORDER BY m, {item}) AS prev, x FROM c JOIN m ON c.b = m.b AND c.{item} = m.t),
z AS (SELECT b, max(CASE WHEN prev >= x THEN prev - x ELSE 0 END) AS r, max(CASE WHEN prev >= x THEN 1 ELSE 0 END) = 0 AS holds FROM s GROUP BY b) SELECT {SHOW} FROM z"""


@query("coherence_order_vars", _order_sql("o", "i"))
def coherence_order_vars(spark, sf_dir):
    return _shown(H.order_preserving(biclusters(spark, sf_dir, "order")))


@query("coherence_order_obs", _order_sql("i", "o"))
def coherence_order_obs(spark, sf_dir):
    return _shown(H.order_preserving(biclusters(spark, sf_dir, "order"), "obs"))


@query("pattern_fit", f"""WITH {bicluster_sql('raw')}, f AS (SELECT b, o, i, x, avg(x) OVER (PARTITION BY b, i) AS mu, avg(x) OVER (PARTITION BY b, o) - avg(x) OVER (PARTITION BY b) AS g FROM c)
SELECT b::INT AS bicluster_id, i::INT AS var_id, round(min(mu), 6) AS mu, round(avg(abs(x - mu - g)), 6) AS noise FROM f GROUP BY b, i""")
def pattern_fit(spark, sf_dir):
    got = H.fit_pattern(biclusters(spark, sf_dir, "raw"))
    return got.select(F.col("bicluster_id").cast("int").alias("bicluster_id"), F.col("var_id").cast("int").alias("var_id"), F.round("mu", 6).alias("mu"), F.round("noise", 6).alias("noise"))


@query("merit_variance", f"WITH {bicluster_sql('raw')} SELECT b::INT AS bicluster_id, round(var_pop(x), 6) AS merit FROM c GROUP BY b")
def merit_variance(spark, sf_dir):
    return H.merit_variance(biclusters(spark, sf_dir, "raw")).select(F.col("bicluster_id").cast("int").alias("bicluster_id"), F.round("merit", 6).alias("merit"))
