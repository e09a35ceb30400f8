"""Structured Streaming queries; their twins are the batch results."""

from __future__ import annotations

from pyspark.sql import functions as F

from querygrade.queries import query, rounded
from querygrade.sources.tables import table
from querygrade.streaming.board import board_ranks, drained, event_stream, live_leaderboard, newest


@query("live_leaderboard", "SELECT CAST(ts AS DATE) AS day, CAST(user_id % 25 AS INTEGER) AS model_id, count(*) AS n, count(*) FILTER (WHERE event_type = 'error') AS errors, round(sum(value), 2) AS seconds FROM events GROUP BY 1, 2")
def leaderboard(spark, sf):
    return rounded(live_leaderboard(event_stream(spark, sf)), "seconds", digits=2)


@query("leaderboard_watermarked", "SELECT CAST(ts AS DATE) AS day, CAST(user_id % 25 AS INTEGER) AS model_id, count(*) AS n, count(*) FILTER (WHERE event_type = 'error') AS errors, round(sum(value), 2) AS seconds FROM events GROUP BY 1, 2")
def leaderboard_watermarked(spark, sf):
    # one trigger reads the whole table, so no row is late
    return rounded(live_leaderboard(event_stream(spark, sf), "2 days"), "seconds", digits=2)


@query("leaderboard_ranks", "WITH t AS (SELECT CAST(user_id % 25 AS INTEGER) AS model_id, count(*) AS n, count(*) FILTER (WHERE event_type = 'error') AS errors, sum(value) AS seconds FROM events GROUP BY 1), r AS (SELECT model_id, n, errors, round(errors / n, 6) AS error_rate, round(seconds / n, 4) AS mean_seconds FROM t) SELECT *, CAST(rank() OVER (ORDER BY error_rate, mean_seconds) AS INTEGER) AS rank, errors || ' errors in ' || n || ' answers' AS reason FROM r")
def leaderboard_ranks(spark, sf):
    return board_ranks(live_leaderboard(event_stream(spark, sf)))


@query("stream_tumbling", "SELECT date_trunc('hour', ts) AS at, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    got = newest(drained(s.select(F.col("w.start").alias("at"), "event_type", "n"), "update", "tumbling"), ["at", "event_type"])
    return got.withColumn("at", F.col("at").cast("timestamp_ntz"))


@query("stream_sliding", "SELECT date_trunc('hour', ts) - INTERVAL (k) HOUR AS at, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1")
def stream_sliding(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return newest(drained(s.select(F.col("w.start").alias("at"), "n"), "update", "sliding"), ["at"]).withColumn("at", F.col("at").cast("timestamp_ntz"))


@query("stream_session", "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, count(DISTINCT k) AS sessions, count(*) AS n FROM s GROUP BY 1")
def stream_session(spark, sf):
    # session windows merge as rows arrive, so the state is read when complete
    s = event_stream(spark, sf).groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("k"))
    rows = drained(s.select(F.col("w.start").alias("at"), "user_id", "k"), "complete", "session")
    last = rows.where(F.col("trigger") == rows.agg(F.max("trigger")).first()[0])
    return last.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("k").alias("n"))


@query("stream_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT user_id, event_type, CAST(ts AS DATE) FROM events)")
def stream_dedup(spark, sf):
    s = event_stream(spark, sf).withColumn("day", F.col("ts").cast("date")).dropDuplicates(["user_id", "event_type", "day"]).select("user_id", "event_type", "day")
    return drained(s, "append", "dedup").agg(F.count(F.lit(1)).alias("n"))


@query("stream_static_join", "SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY 1")
def stream_static_join(spark, sf):
    nation = table(spark, sf, "nation").select(F.col("n_nationkey").alias("model_id"), "n_name")
    s = event_stream(spark, sf).join(F.broadcast(nation), "model_id").groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))
    return newest(drained(s, "update", "static-join"), ["n_name"])
