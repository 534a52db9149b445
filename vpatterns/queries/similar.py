"""Similarity measures and grouping of variables (M-01..12, B-01..06)."""

from __future__ import annotations

from pyspark.sql import functions as F

from vpatterns.operators import clustering as C
from vpatterns.operators import prepare as P
from vpatterns.operators import similarity as S
from vpatterns.queries import query
from vpatterns.queries import views as V
from vpatterns.sources import workloads as WL
from vpatterns.sources.tables import load

K = 8


def _rounded(df, *columns):
    return df.select("a", "b", *[F.round(c, 6).alias(c) for c in columns])


def brand_cells(spark, sf_dir, k=K):
    m = WL.brands(spark, sf_dir)
    variables = P.top_variables(m.cells, k)
    return m, variables, m.cells.join(F.broadcast(variables), "item").select("obs", "var_id", F.lit(1).alias("level"))


LINE = {"l_returnflag": "ascii(l_returnflag)", "l_linestatus": "ascii(l_linestatus)", "l_quantity": "CAST(floor((l_quantity - 1) / 12.5) AS INT)", "l_discount": "CAST(floor(l_discount * 100 / 4) AS INT)", "l_tax": "CAST(floor(l_tax * 100 / 3) AS INT)"}


def line_cells(spark, sf_dir):
    """obs, var_id 0-4, level of lineitem; discounts under 2 % and tax 0 count as missing."""
    line = load(spark, sf_dir, "lineitem").withColumn("obs", F.monotonically_increasing_id())
    levels = [F.expr(e) for e in LINE.values()]
    levels[3], levels[4] = F.when(F.col("l_discount") >= 0.02, levels[3]), F.when(F.col("l_tax") > 0, levels[4])
    cells = line.select("obs", F.posexplode(F.array(*levels)).alias("var_id", "level")).where("level is not null")
    return cells, load(spark, sf_dir, "lineitem").count()


LINE_SQL = """raw AS (SELECT row_number() OVER () AS obs, * FROM lineitem),
cells AS (SELECT obs, v - 1 AS v, l[v] AS l FROM (SELECT obs, [ascii(l_returnflag), ascii(l_linestatus), floor((l_quantity - 1) / 12.5)::INT, CASE WHEN l_discount >= 0.02 THEN floor(l_discount * 100 / 4)::INT END, CASE WHEN l_tax > 0 THEN floor(l_tax * 100 / 3)::INT END] AS l FROM raw), (SELECT unnest(range(1, 6)) AS v) WHERE l[v] IS NOT NULL),
n AS (SELECT count(*)::DOUBLE AS n FROM lineitem)"""
BRAND_SQL = f"{V.BRANDS}, vars AS (SELECT item, row_number() OVER (ORDER BY f DESC, item) - 1 AS v FROM (SELECT item, count(*) AS f FROM it GROUP BY item ORDER BY f DESC, item LIMIT {K})), cells AS (SELECT obs, v, 1 AS l FROM it JOIN vars USING (item))"
GRID = """grid AS (SELECT o.obs, v.v, coalesce(c.l, -1) AS l FROM (SELECT obs FROM raw) o CROSS JOIN (SELECT DISTINCT v FROM cells) v LEFT JOIN cells c ON c.obs = o.obs AND c.v = v.v)"""
JOINT = "j AS (SELECT x.v AS a, y.v AS b, x.l AS la, y.l AS lb, count(*) AS c FROM cells x JOIN cells y ON x.obs = y.obs AND x.v < y.v GROUP BY ALL), s AS (SELECT v, l, count(*) AS c FROM cells GROUP BY v, l)"
SCORE = """r AS (SELECT j.a, j.b, avg(j.c / greatest(x.c, y.c)) AS purity, 1 + sum(j.c / n.n * ln(j.c / n.n)) / ln(min(n.n)) AS concentration FROM j JOIN s x ON x.v = a AND x.l = la JOIN s y ON y.v = b AND y.l = lb, n GROUP BY j.a, j.b)"""
FULL = "SELECT a::INT AS a, b::INT AS b, round(purity, 6) AS purity, round(concentration, 6) AS concentration, round(purity * concentration, 6) AS sim FROM r"


@query("sim_constant_order_brand", f"WITH {BRAND_SQL}, {JOINT}, {SCORE} {FULL}")
def sim_constant_order_brand(spark, sf_dir):
    m, _, cells = brand_cells(spark, sf_dir)
    return _rounded(S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs), "purity", "concentration", "sim")


@query("sim_constant_signatures", f"WITH {BRAND_SQL}, {JOINT}, {SCORE} {FULL}")
def sim_constant_signatures(spark, sf_dir):
    m, variables, _ = brand_cells(spark, sf_dir)
    sig = P.signatures(m.cells, variables)
    return _rounded(S.pattern_similarity(S.joint_counts_of_signatures(sig), S.marginals_of_signatures(sig), m.n_obs), "purity", "concentration", "sim")


@query("sim_constant_gram", f"WITH {LINE_SQL}, {JOINT}, {SCORE} {FULL}")
def sim_constant_gram(spark, sf_dir):
    cells, n = line_cells(spark, sf_dir)
    columns = sorted((r["var_id"], r["level"]) for r in cells.select("var_id", "level").distinct().collect())
    return _rounded(S.pattern_similarity(S.joint_counts_gram(cells, columns), S.marginals(cells), n), "purity", "concentration", "sim")


def _line(missing, *columns):
    def run(spark, sf_dir):
        cells, n = line_cells(spark, sf_dir)
        return _rounded(S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), n, missing), *columns)

    return run


query("sim_constant_lineitem", f"WITH {LINE_SQL}, {JOINT}, {SCORE} {FULL}")(_line("skip", "purity", "concentration", "sim"))
query("sim_purity", f"WITH {LINE_SQL}, {JOINT}, {SCORE} SELECT a::INT AS a, b::INT AS b, round(purity, 6) AS purity FROM r")(_line("skip", "purity"))
query("sim_concentration", f"WITH {LINE_SQL}, {JOINT}, {SCORE} SELECT a::INT AS a, b::INT AS b, round(concentration, 6) AS concentration FROM r")(_line("skip", "concentration"))
query("sim_missing_level", f"WITH {LINE_SQL}, {GRID}, {JOINT.replace('cells', 'grid')}, {SCORE} {FULL}")(_line("level", "purity", "concentration", "sim"))
query("sim_missing_pairwise", f"""WITH {LINE_SQL}, {JOINT}, m AS (SELECT *, sum(c) OVER (PARTITION BY a, b, la) AS ca, sum(c) OVER (PARTITION BY a, b, lb) AS cb, sum(c) OVER (PARTITION BY a, b)::DOUBLE AS t FROM j),
r AS (SELECT a, b, avg(c / greatest(ca, cb)) AS purity, 1 + sum(c / t * ln(c / t)) / ln(min(t)) AS concentration FROM m GROUP BY a, b) {FULL}""")(_line("pairwise", "purity", "concentration", "sim"))


@query("sim_partner_counts", f"WITH {LINE_SQL}, {JOINT} SELECT a::INT AS a, b::INT AS b, la::INT AS la, count(DISTINCT lb)::BIGINT AS partners FROM j GROUP BY a, b, la")
def sim_partner_counts(spark, sf_dir):
    cells, _ = line_cells(spark, sf_dir)
    return S.partner_counts(S.joint_counts(cells)).select("a", "b", "la", "partners")


def grid_values(spark, sf_dir, dims=64, width=0.05):
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obs"), F.posexplode(F.slice("embedding", 1, dims)).alias("var", "v"))
    return e.select("obs", "var", F.floor(F.col("v").cast("double") / F.lit(width)).cast("long").alias("value"))


GRID_SQL = "g AS (SELECT vec_id AS obs, generate_subscripts(embedding, 1) - 1 AS v, floor(unnest(embedding)::DOUBLE / 0.05::DOUBLE)::BIGINT AS x FROM embeddings), n AS (SELECT count(*)::DOUBLE AS n FROM embeddings)"


def _difference_sql(values: str, d: str, where: str = "") -> str:
    return f"""WITH {values}, j AS (SELECT x.v AS a, y.v AS b, {d} AS d, count(*) AS c FROM g x JOIN g y ON x.obs = y.obs AND x.v < y.v WHERE true {where} GROUP BY ALL),
r AS (SELECT a, b, 1.0::DOUBLE / count(*) AS purity, 1 + sum(c / n * ln(c / n)) / ln(min(n)) AS concentration FROM j, n GROUP BY a, b) {FULL}"""


@query("sim_additive_embeddings", _difference_sql(GRID_SQL, "y.x - x.x"))
def sim_additive_embeddings(spark, sf_dir):
    values = grid_values(spark, sf_dir)
    return _rounded(S.difference_similarity(values, load(spark, sf_dir, "embeddings").count()), "purity", "concentration", "sim")


@query("sim_multiplicative_lineitem", _difference_sql("w AS (SELECT row_number() OVER () AS obs, [l_quantity::BIGINT, round(l_discount * 100)::BIGINT, round(l_tax * 100)::BIGINT] AS l FROM lineitem), g AS (SELECT obs, k - 1 AS v, l[k] AS x FROM w, (SELECT unnest([1, 2, 3]) AS k)), n AS (SELECT count(*)::DOUBLE AS n FROM lineitem)", "round(y.x / x.x, 9)", "AND x.x <> 0 AND y.x <> 0"))
def sim_multiplicative_lineitem(spark, sf_dir):
    line = load(spark, sf_dir, "lineitem").withColumn("obs", F.monotonically_increasing_id())
    whole = F.array(F.col("l_quantity").cast("long"), F.round(F.col("l_discount") * 100).cast("long"), F.round(F.col("l_tax") * 100).cast("long"))
    values = line.select("obs", F.posexplode(whole).alias("var", "value"))
    return _rounded(S.difference_similarity(values, line.count(), "multiplicative"), "purity", "concentration", "sim")


def wide_embeddings(spark, sf_dir, dims=64):
    e = load(spark, sf_dir, "embeddings")
    return e.select("vec_id", *[F.element_at("embedding", i + 1).cast("double").alias(f"y{i}") for i in range(dims)])


@query("sim_order_embeddings", "WITH g AS (SELECT vec_id AS obs, generate_subscripts(embedding, 1) - 1 AS v, unnest(embedding)::DOUBLE AS x FROM embeddings) SELECT x.v::INT AS a, y.v::INT AS b, round(greatest(sum((x.x > y.x)::INT), sum((x.x < y.x)::INT)) / count(*), 6) AS sim FROM g x JOIN g y ON x.obs = y.obs AND x.v < y.v GROUP BY x.v, y.v")
def sim_order_embeddings(spark, sf_dir):
    return _rounded(S.order_similarity(wide_embeddings(spark, sf_dir), [f"y{i}" for i in range(64)]), "sim")


NUM = ["l_quantity", "l_discount", "l_tax"]
_PAIRS = [(0, 1), (0, 2), (1, 2)]


@query("sim_order_lineitem", " UNION ALL ".join(f"SELECT {i} AS a, {j} AS b, round(greatest(sum(({NUM[i]} > {NUM[j]})::INT), sum(({NUM[i]} < {NUM[j]})::INT)) / count(*), 6) AS sim FROM lineitem" for i, j in _PAIRS))
def sim_order_lineitem(spark, sf_dir):
    return _rounded(S.order_similarity(load(spark, sf_dir, "lineitem"), NUM), "sim")


@query("base_jaccard", f"WITH {BRAND_SQL}, {JOINT}, q AS (SELECT v, sum(c) AS c FROM s GROUP BY v) SELECT a.v::INT AS a, b.v::INT AS b, round(coalesce(m, 0) / (a.c + b.c - coalesce(m, 0)), 6) AS score FROM q a JOIN q b ON a.v < b.v LEFT JOIN (SELECT a AS ja, b AS jb, sum(c) AS m FROM j WHERE la = lb GROUP BY a, b) ON ja = a.v AND jb = b.v")
def base_jaccard(spark, sf_dir):
    _, _, cells = brand_cells(spark, sf_dir)
    return _rounded(S.jaccard(S.joint_counts(cells), S.marginals(cells)), "score")


@query("base_pearson", " UNION ALL ".join(f"SELECT {i} AS a, {j} AS b, round(corr({NUM[i]}, {NUM[j]}), 6) AS score FROM lineitem" for i, j in _PAIRS))
def base_pearson(spark, sf_dir):
    return _rounded(S.pearson(load(spark, sf_dir, "lineitem"), NUM), "score")


def _kendall_sql(form: str) -> str:
    below = "n0" if form == "a" else "sqrt((n0 - n1) * (n0 - n2))"
    return f"""WITH {LINE_SQL}, {JOINT}, t AS (SELECT x.a, x.b, sum(x.c::DOUBLE * y.c * sign(y.lb - x.lb)) AS s FROM j x JOIN j y ON x.a = y.a AND x.b = y.b AND x.la < y.la GROUP BY x.a, x.b),
p AS (SELECT a, b, sum(c)::DOUBLE AS n FROM j GROUP BY a, b), q AS (SELECT a, b, sum(c * (c - 1) / 2.0::DOUBLE) AS n1 FROM (SELECT a, b, la, sum(c) AS c FROM j GROUP BY ALL) GROUP BY a, b), o AS (SELECT a, b, sum(c * (c - 1) / 2.0::DOUBLE) AS n2 FROM (SELECT a, b, lb, sum(c) AS c FROM j GROUP BY ALL) GROUP BY a, b),
z AS (SELECT p.a, p.b, coalesce(s, 0) AS s, n * (n - 1) / 2 AS n0, n1, n2 FROM p JOIN q ON p.a = q.a AND p.b = q.b JOIN o ON p.a = o.a AND p.b = o.b LEFT JOIN t ON t.a = p.a AND t.b = p.b)
SELECT a::INT AS a, b::INT AS b, round(s / {below}, 6) AS score FROM z"""


def _kendall(form):
    def run(spark, sf_dir):
        cells, _ = line_cells(spark, sf_dir)
        return _rounded(S.kendall(S.joint_counts(cells), form), "score")

    return run


for _form in "ab":
    query(f"base_kendall_{_form}", _kendall_sql(_form))(_kendall(_form))


# Five planted variables, alike in their differences on every fourth vector, and hardly correlated.
@query("pearson_blind_spot", """WITH e AS (SELECT vec_id AS obs, list_transform(embedding[16:20], lambda v: floor(v::DOUBLE / 0.01::DOUBLE)::BIGINT) AS g FROM embeddings),
r AS (SELECT obs, i AS var, CASE WHEN obs % 4 = 3 THEN ([7, -3, 0, 12, 5])[i - 15] ELSE g[i - 15] END AS x FROM e, (SELECT unnest(range(16, 21)) AS i)), n AS (SELECT count(*)::DOUBLE AS n FROM embeddings),
b AS (SELECT a.var AS a, b.var AS b, a.x AS x, b.x AS y FROM r a JOIN r b ON a.obs = b.obs AND a.var < b.var), d AS (SELECT a, b, y - x AS d, count(*) AS c FROM b GROUP BY ALL)
SELECT a::INT AS a, b::INT AS b, pearson, additive_sim, best_support FROM (SELECT a, b, round(corr(x, y), 6) + 0.0 AS pearson FROM b GROUP BY ALL)
JOIN (SELECT a, b, round(1.0::DOUBLE / count(*) * (1 + sum(c / n * ln(c / n)) / ln(min(n))), 6) AS additive_sim, max(c) / min(n) AS best_support FROM d, n GROUP BY ALL) USING (a, b)""")
def pearson_blind_spot(spark, sf_dir):
    values = WL.planted_numeric(spark, sf_dir).where("var between 16 and 20")
    names = [f"y{v}" for v in range(16, 21)]
    rows = values.groupBy("obs").pivot("var", list(range(16, 21))).agg(F.first("value")).toDF("obs", *names)
    n = rows.count()
    r = S.pearson(rows, names).select((F.col("a") + 16).alias("a"), (F.col("b") + 16).alias("b"), (F.round("score", 6) + 0.0).alias("pearson"))
    sim = S.difference_similarity(values, n).select("a", "b", F.round("sim", 6).alias("additive_sim"))
    x, y = (values.select("obs", F.col("var").alias(v), F.col("value").alias(f"{v}v")) for v in "ab")
    top = x.join(y, "obs").where("a < b").groupBy("a", "b", (F.col("bv") - F.col("av")).alias("d")).count().groupBy("a", "b").agg((F.max("count") / n).alias("best_support"))
    return r.join(sim, ["a", "b"]).join(top, ["a", "b"])


def cluster_sql(linkage: str = "avg", direction: str = "DESC", cap: int = 4) -> str:
    """One fusion a step of the recursion, from the pair table."""
    return f"""WITH RECURSIVE {BRAND_SQL}, {JOINT}, {SCORE},
sim AS (SELECT a::INT AS a, b::INT AS b, purity * concentration AS s FROM r),
st AS (SELECT 0 AS step, list_transform(range(0, {K}), lambda x: x::INT) AS c
UNION ALL SELECT step + 1, list_transform(c, lambda x: CASE WHEN x = v THEN u ELSE x END) FROM (
  SELECT step, c, u, v FROM (
    SELECT step, c, u, v, row_number() OVER (ORDER BY round(s, 9) {direction}, u, v) AS k FROM (
      SELECT step, c, least(c[a + 1], c[b + 1]) AS u, greatest(c[a + 1], c[b + 1]) AS v, {linkage}(s) AS s FROM st, sim
      WHERE c[a + 1] <> c[b + 1] GROUP BY ALL)
    WHERE len(list_filter(c, lambda x: x = u OR x = v)) <= {cap}) WHERE k = 1)),
fin AS (SELECT c FROM st ORDER BY step DESC LIMIT 1)
SELECT i::INT AS var_id, c[i + 1]::INT AS cluster_id FROM fin, (SELECT unnest(range(0, {K})) AS i)"""


def _clusters(linkage="average", direction="similar", cap=4):
    def run(spark, sf_dir):
        m, _, cells = brand_cells(spark, sf_dir)
        sim = S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs)
        return C.capped_clusters(sim, list(range(K)), cap, linkage, direction)

    return run


query("clusters_similar", cluster_sql())(_clusters())
query("clusters_single", cluster_sql("max"))(_clusters("single"))
query("clusters_complete", cluster_sql("min"))(_clusters("complete"))
query("clusters_dissimilar", cluster_sql(direction="ASC"))(_clusters(direction="dissimilar"))
query("clusters_cap_5", cluster_sql(cap=5))(_clusters(cap=5))
query("clusters_cap_8", cluster_sql(cap=8))(_clusters(cap=8))
RANDOM = f"rc AS (SELECT v, min(v) OVER (PARTITION BY g) AS c FROM (SELECT v, floor((row_number() OVER (ORDER BY md5('42:' || item), item) - 1) / 4) AS g FROM vars))"


@query("clusters_random", f"WITH {BRAND_SQL}, {RANDOM} SELECT v::INT AS var_id, c::INT AS cluster_id FROM rc")
def clusters_random(spark, sf_dir):
    _, variables, _ = brand_cells(spark, sf_dir)
    return C.random_clusters(variables, 4)


@query("clusters_distributed")
def clusters_distributed(spark, sf_dir):
    m, variables, cells = brand_cells(spark, sf_dir)
    sim = S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs)
    return C.capped_clusters_df(sim, variables.select(F.col("var_id").cast("int").alias("var_id")), 4)


@query("related_overlapping_clusters", f"""WITH {BRAND_SQL}, {JOINT}, {SCORE}, s2 AS (SELECT a, b, purity * concentration AS s FROM r UNION ALL SELECT b, a, purity * concentration FROM r)
SELECT a::INT AS cluster_id, b::INT AS var_id FROM (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS k FROM s2) WHERE k < 4 UNION SELECT DISTINCT a::INT, a::INT FROM s2""")
def related_overlapping_clusters(spark, sf_dir):
    m, _, cells = brand_cells(spark, sf_dir)
    return C.overlapping_clusters(S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs), 4)


@query("cluster_quality", f"""WITH {BRAND_SQL}, {RANDOM}, {JOINT}, {SCORE}, e AS (SELECT purity * concentration AS s, x.c AS ca, y.c AS cb FROM r JOIN rc x ON x.v = a JOIN rc y ON y.v = b),
f AS (SELECT ca AS c, s, ca = cb AS i FROM e UNION ALL SELECT cb, s, false FROM e WHERE ca <> cb)
SELECT g.c::INT AS cluster_id, g.n::BIGINT AS n_vars, round(avg(s) FILTER (WHERE i), 6) AS intra, round(avg(s) FILTER (WHERE NOT i), 6) AS inter FROM (SELECT c, count(*) AS n FROM rc GROUP BY c) g LEFT JOIN f ON f.c = g.c GROUP BY g.c, g.n""")
def cluster_quality(spark, sf_dir):
    m, variables, cells = brand_cells(spark, sf_dir)
    sim = S.pattern_similarity(S.joint_counts(cells), S.marginals(cells), m.n_obs)
    got = C.cluster_quality(sim, C.random_clusters(variables, 4))
    return got.select("cluster_id", "n_vars", F.round("intra", 6).alias("intra"), F.round("inter", 6).alias("inter"))
