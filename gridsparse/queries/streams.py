"""Streaming queries over the event table replayed from files; each ends in the state of the batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from gridsparse.queries.catalog import register, sql
from gridsparse.sources.tables import Tables, read_table
from gridsparse.streaming import rows, updates


def _events(spark, sf_dir):
    return updates.replay(spark, read_table(spark, sf_dir, "events"))


@register("stream_extend_add", sql("SELECT i, j, v FROM ut", "ut"))
def stream_extend_add(spark, sf_dir):
    code = F.array_position(F.array(*map(F.lit, Tables.EVENT_TYPES)), F.col("event_type")) - 1
    cells = _events(spark, sf_dir).select(F.col("user_id").alias("i"), code.alias("j"), F.lit(1).cast("long").alias("v"))
    return updates.apply_updates(cells).read()


@register("stream_assign_last", "SELECT user_id AS i, CAST(date_part('day', ts) AS BIGINT) AS j, arg_max(event_id, ts) AS v FROM events GROUP BY ALL")
def stream_assign_last(spark, sf_dir):
    cells = _events(spark, sf_dir).select(F.col("user_id").alias("i"), F.dayofmonth("ts").cast("long").alias("j"), F.col("event_id").alias("v"), F.col("ts").alias("at"))
    return updates.apply_updates(cells, "assign").read().select("i", "j", "v")


@register("r48_row_store", "SELECT user_id AS i, CAST(date_part('day', ts) AS BIGINT) AS j, arg_max(event_id, ts) AS v FROM events GROUP BY ALL")
def r48_row_store(spark, sf_dir):
    """The same cells, each user's row in the state of the stream."""
    cells = _events(spark, sf_dir).select(F.col("user_id").alias("i"), F.dayofmonth("ts").cast("long").alias("j"), F.col("event_id").alias("v"), F.col("ts").alias("at"))
    return rows.row_store(cells).select("i", "j", "v")


@register("stream_windows", "SELECT CAST(date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS INTEGER) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_windows(spark, sf_dir):
    counts = updates.run_to_table(updates.windowed_counts(_events(spark, sf_dir)), "complete")
    return counts.select(F.datediff(F.to_date("start"), F.lit("1970-01-01").cast("date")).alias("day"), "event_type", "n")


@register("stream_dedup", "SELECT event_id, user_id FROM events")
def stream_dedup(spark, sf_dir):
    events = read_table(spark, sf_dir, "events")
    twice = updates.replay(spark, events.unionByName(events))
    return updates.run_to_table(updates.deduplicated(twice).select("event_id", "user_id"))


@register("stream_static_join", "SELECT event_id, n_name FROM events JOIN nation ON user_id % 25 = n_nationkey")
def stream_static_join(spark, sf_dir):
    nation = read_table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    joined = _events(spark, sf_dir).withColumn("k", F.col("user_id") % 25).join(F.broadcast(nation), F.col("k") == F.col("n_nationkey"))
    return updates.run_to_table(joined.select("event_id", "n_name"))


@register("r45_sliding_windows", "SELECT date_diff('hour', TIMESTAMP '1970-01-01', h) + o AS start_hour, count(*) AS n FROM (SELECT date_trunc('hour', ts) AS h FROM events) CROSS JOIN (SELECT unnest([0, -1]) AS o) GROUP BY 1")
def r45_sliding_windows(spark, sf_dir):
    """Two-hour windows every hour."""
    e = read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    counts = e.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return counts.select((F.unix_timestamp("w.start") / 3600).cast("long").alias("start_hour"), "n")


@register("r45_session_windows", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, count(DISTINCT k) AS sessions, count(*) AS events FROM s GROUP BY 1")
def r45_session_windows(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    sessions = e.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return sessions.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))
