"""Batch twins of the streaming operators (W18)."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipflow.sources.standin import epoch
from clipflow.sources.tables import load
from clipflow.streaming import clips as C
from clipflow.workloads.registry import query


def _events(spark, d):
    return load(spark, d, "events", "event_id", "user_id", "ts", "value").select("event_id", "user_id", epoch("ts").alias("e"), "value")


@query("st_tumbling", "SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) * 3600 AS start, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def st_tumbling(spark, d):
    """By arithmetic on seconds, so that the session's zone does not matter; equal to the window operator in UTC."""
    e = _events(spark, d).groupBy((F.floor(F.col("e") / 3600) * 3600).alias("start"))
    return e.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("st_sliding", "SELECT (CAST(floor(epoch(ts) / 3600) AS BIGINT) - k) * 3600 AS start, count(*) AS n FROM events, (SELECT unnest(range(0, 6)) AS k) GROUP BY 1")
def st_sliding(spark, d):
    hours = _events(spark, d).groupBy(F.floor(F.col("e") / 3600).alias("h")).agg(F.count(F.lit(1)).alias("n"))  # hours first: six copies of a sum, not of an event
    return hours.select(F.explode(F.expr("transform(sequence(0L, 5L), k -> (h - k) * 3600)")).alias("start"), "n").groupBy("start").agg(F.sum("n").alias("n"))


@query("st_session", """WITH a AS (SELECT user_id, event_id, epoch(ts) AS e, lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events),
    b AS (SELECT *, sum(CASE WHEN p IS NULL OR e - p >= 43200 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY e, event_id) AS s FROM a)
    SELECT user_id, round(min(e), 3) AS s0, round(max(e), 3) AS s1, count(*) AS n FROM b GROUP BY user_id, s""")
def st_session(spark, d):
    return C.sessions_batch(_events(spark, d)).select("user_id", F.round("s0", 3).alias("s0"), F.round("s1", 3).alias("s1"), "n")
