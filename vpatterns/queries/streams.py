"""Streaming results against the same rows in one batch."""

from __future__ import annotations

from pyspark.sql import functions as F

from vpatterns.operators import similarity as S
from vpatterns.queries import query
from vpatterns.sources.tables import load
from vpatterns.streaming import events as E

DAY = "strftime({}, '%Y-%m-%d')"


def _shown(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd"))


@query("stream_tumbling", f"SELECT {DAY.format('ts')} AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return _shown(E.finished(E.tumbling(E.event_stream(spark, sf_dir))))


@query("stream_sliding", f"SELECT {DAY.format('ts - to_days(k::INT)')} AS start, event_type, count(*)::BIGINT AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    return _shown(E.finished(E.sliding(E.event_stream(spark, sf_dir))))


@query("stream_session", """WITH l AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS f FROM events),
g AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM l) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*)::BIGINT AS n FROM g GROUP BY user_id, s""")
def stream_session(spark, sf_dir):
    got = E.finished(E.sessions(E.event_stream(spark, sf_dir)))
    return got.select("user_id", F.unix_micros("start").alias("start_us"), "n")


@query("stream_dedup", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1")
def stream_dedup(spark, sf_dir):
    got = E.finished(E.deduplicated(E.event_stream(spark, sf_dir)).select("event_id", "event_type"), "append")
    return got.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_join(spark, sf_dir):
    return E.finished(E.click_to_purchase(E.event_stream(spark, sf_dir)), "append")


@query("stream_static_join", "SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return E.finished(E.with_segment(E.event_stream(spark, sf_dir), customers).select("event_id", "c_mktsegment"), "append")


@query("stream_user_state", "WITH k AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS i FROM (SELECT DISTINCT event_type FROM events)) SELECT user_id, sum(DISTINCT 1::BIGINT << i::INT)::BIGINT AS mask FROM events JOIN k USING (event_type) GROUP BY 1")
def stream_user_state(spark, sf_dir):
    kinds = sorted(r[0] for r in load(spark, sf_dir, "events").select("event_type").distinct().collect())
    got = E.finished(E.level_masks(E.event_stream(spark, sf_dir), kinds), "update")
    return got.groupBy("user_id").agg(F.max("mask").alias("mask"))


@query("stream_similarity", """WITH it AS (SELECT DISTINCT user_id, ts::DATE AS day, event_type FROM events), k AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS v FROM (SELECT DISTINCT event_type FROM it)),
cells AS (SELECT user_id || '/' || day AS obs, v, 1 AS l FROM it JOIN k USING (event_type)), n AS (SELECT count(DISTINCT obs)::DOUBLE AS n FROM cells),
j AS (SELECT x.v AS a, y.v AS b, count(*) AS c FROM cells x JOIN cells y ON x.obs = y.obs AND x.v < y.v GROUP BY 1, 2), s AS (SELECT v, count(*) AS c FROM cells GROUP BY 1)
SELECT a::INT AS a, b::INT AS b, round(j.c / greatest(x.c, y.c) * (1 + j.c / n * ln(j.c / n) / ln(n)), 6) AS sim FROM j JOIN s x ON x.v = a JOIN s y ON y.v = b, n""")
def stream_similarity(spark, sf_dir):
    cells = E.CoOccurrence().run(E.event_stream(spark, sf_dir))
    kinds = sorted(r[0] for r in cells.select("event_type").distinct().collect())
    at = F.create_map(*[F.lit(x) for i, k in enumerate(kinds) for x in (k, i)])
    rows = cells.select(F.concat_ws("/", F.col("user_id").cast("string"), F.col("day").cast("string")).alias("obs"), at[F.col("event_type")].alias("var_id"), F.lit(1).alias("level"))
    n = rows.select("obs").distinct().count()
    return S.pattern_similarity(S.joint_counts(rows), S.marginals(rows), n).select("a", "b", F.round("sim", 6).alias("sim"))
