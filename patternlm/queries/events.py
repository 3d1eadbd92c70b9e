"""Batch twins of the streaming operators."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from patternlm.queries import query
from patternlm.sources.io import table


def events(spark, d):
    return table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("""SELECT event_id, user_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_hour FROM events""")
def q_win_range(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros("ts")).rangeBetween(-3_600_000_000, 0)
    return events(spark, d).select("event_id", "user_id", F.count("*").over(w).alias("last_hour"))


@query("SELECT epoch_us(date_trunc('day', ts)) // 1000000 AS start_s, event_type, count(*) AS n FROM events GROUP BY ALL")
def q_tumbling(spark, d):
    g = events(spark, d).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return g.select(F.unix_seconds("w.start").alias("start_s"), "event_type", "n")


@query("""SELECT s.start_s, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // 1000000 // 1800 * 1800, epoch_us(ts) // 1000000 // 1800 * 1800 - 1800]) AS start_s FROM events) s GROUP BY s.start_s""")
def q_sliding(spark, d):
    g = events(spark, d).groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return g.select(F.unix_seconds("w.start").alias("start_s"), "n")


@query("""WITH e AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 7200000000 THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t) AS k FROM e)
SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, k""")
def q_session(spark, d):
    g = events(spark, d).groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@query("""SELECT a.event_id AS error_id, b.event_id AS signup_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'signup'
AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""")
def q_interval_join(spark, d):
    e = events(spark, d)
    a = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("t0"))
    b = e.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), "user_id", F.col("ts").alias("t1"))
    return a.join(b, "user_id").where("t1 >= t0 AND t1 <= t0 + INTERVAL 1 HOUR").select("error_id", "signup_id")
