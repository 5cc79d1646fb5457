"""Streams run to the end of what has arrived; each must equal its batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecgraph.operators import quantize
from vecgraph.sources import sets
from vecgraph.streaming import streams as S

from .common import BOOK, CODES, ISO, K, M, query, sql


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling_qps(spark, d):
    return S.finished(S.tumbling(S.source(spark, d, "events")), "complete").withColumn("start", S.wall("start"))


@query("SELECT s AS start, count(*) AS n, round(sum(value), 4) AS value FROM (SELECT value, unnest(list_transform(range(4), lambda i: time_bucket(INTERVAL 6 HOURS, ts) - to_hours(6 * i))) AS s FROM events) GROUP BY s")
def stream_sliding(spark, d):
    return S.finished(S.sliding(S.source(spark, d, "events")), "complete").withColumn("start", S.wall("start"))


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTES OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e)
SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTES AS "end", count(*) AS n FROM g GROUP BY user_id, s""")
def stream_session(spark, d):
    got = S.finished(S.sessions(S.source(spark, d, "events")), "complete")
    return got.select("user_id", S.wall("start").alias("start"), S.wall("end").alias("end"), "n")


@query("SELECT DISTINCT user_id, event_type, date_trunc('hour', ts)::TIMESTAMP AS hour FROM events")
def stream_dedup(spark, d):
    return S.finished(S.first_seen(S.source(spark, d, "events"))).withColumn("hour", S.wall("hour"))


@query("""WITH m AS (SELECT max(ts) - INTERVAL 1 DAY AS mark FROM events)
SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS n FROM events, m GROUP BY 1, mark HAVING time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= mark""")
def stream_late_rows(spark, d):
    return S.finished(S.closed_windows(S.source(spark, d, "events"))).withColumn("start", S.wall("start"))


@query("SELECT event_id, user_id, c_mktsegment AS segment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    users = sets.table(spark, d, "customer").select(F.col("c_custkey").alias("uid"), F.col("c_mktsegment").alias("segment"))
    return S.finished(S.enriched(S.source(spark, d, "events"), users))


@query(sql(ISO, BOOK, CODES, "SELECT vid, array_to_string(code, ',') AS code FROM codes"))
def stream_encode(spark, d):
    """Arriving vectors encoded with a frozen quantizer."""
    model = quantize.seeded_books(sets.iso(spark, d), M, K)
    arriving = S.source(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    return S.finished(quantize.encode(arriving, model).select("vid", F.array_join("code", ",").alias("code")))


@query("SELECT label, count(*) AS n, min(vec_id) AS first, max(vec_id) AS last FROM embeddings GROUP BY label")
def stream_fresh_state(spark, d):
    """The state after the last batch of each label."""
    return S.finished_last(S.fresh_counts(S.source(spark, d, "embeddings")), "label")
