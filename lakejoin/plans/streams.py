"""Streaming queries, held against the batch answers."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..operators import profile as profiles
from ..session import shared_dir
from ..streaming import events
from .registry import query


@query("stream_profile", "SELECT attr, value, CAST(count(*) AS BIGINT) AS cnt FROM (SELECT 'event_type' AS attr, event_type AS value FROM events UNION ALL SELECT 'props', props FROM events) GROUP BY ALL")
def profile(spark, sf_dir):
    return events.incremental_frequencies(events.event_stream(spark, sf_dir), "events").select("attr", "value", "cnt")


@query("stream_windows", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ALL")
def windows(spark, sf_dir):
    found = events.run_to_end(events.windows(events.event_stream(spark, sf_dir)), "complete")
    return found.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query(
    "stream_sessions",
    "WITH f AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC ROWS UNBOUNDED PRECEDING) AS k FROM f) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k",
)
def sessions(spark, sf_dir):
    found = events.run_to_end(events.sessions(events.event_stream(spark, sf_dir)), "complete")
    return found.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("stream_dedup", "SELECT DISTINCT event_id, event_type FROM events")
def dedup(spark, sf_dir):
    return events.run_to_end(events.deduplicated(events.event_stream(spark, sf_dir)).select("event_id", "event_type"), "append")


_LATE = "event_id % 2 = 1 AND ts < (SELECT max(ts) FROM events) - INTERVAL 5 DAY"


@query("stream_late", f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, CAST(count(*) AS BIGINT) AS n FROM events WHERE NOT ({_LATE}) AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 2 DAY GROUP BY ALL")
def late(spark, sf_dir):
    """Odd events of more than five days before the last come in the last of three files, after the watermark has passed them: they
    are dropped, and closed days hold the punctual ones. (A batch drops what the watermark before it has passed.)"""
    table = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    last = table.agg(F.max("ts").alias("last"))
    turn = F.expr("CASE WHEN event_id % 2 = 1 AND ts < last - INTERVAL 5 DAYS THEN 2 WHEN ts >= last - INTERVAL 1 DAY THEN 1 ELSE 0 END")
    marked = table.crossJoin(F.broadcast(last)).withColumn("turn", turn).drop("last")
    root = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    for k in range(3):  # a later file is read later
        marked.where(F.col("turn") == k).drop("turn").coalesce(1).write.mode("append").parquet(root)
    stream = spark.readStream.schema(table.schema).option("maxFilesPerTrigger", 1).parquet(root)
    found = events.run_to_end(events.daily_on_time(stream, "2 days"), "append")
    return found.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


@query("stream_first_seen", "SELECT props AS value, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS first_ts FROM events WHERE props IS NOT NULL GROUP BY ALL")
def first_seen(spark, sf_dir):
    found = events.run_to_end(events.first_seen(events.event_stream(spark, sf_dir), "props"), "append")
    return found.select("value", F.date_format("first_ts", "yyyy-MM-dd HH:mm:ss").alias("first_ts"))


@query("stream_enriched", "WITH c AS (SELECT event_type, count(*) AS n FROM events GROUP BY ALL), p AS (SELECT CAST(count(*) AS BIGINT) AS cardinality, log2(sum(n)) - sum(n * log2(n)) / sum(n) AS entropy FROM c) SELECT event_id, event_type, cardinality, round(entropy, 6) AS entropy FROM events, p")
def enriched(spark, sf_dir):
    """Stream-static join: every event with the profile of the column of its type."""
    static = profiles.profile_dataset(spark.read.parquet(f"{sf_dir}/events.parquet"), "events")
    found = events.run_to_end(events.enriched(events.event_stream(spark, sf_dir), static).select("event_id", "event_type", "cardinality", "entropy"), "append")
    return found.withColumn("entropy", F.round("entropy", 6))


@query("stream_sliding", "SELECT strftime(d, '%Y-%m-%d') AS day, event_type, CAST(count(*) AS BIGINT) AS n FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) q GROUP BY ALL")
def sliding(spark, sf_dir):
    """Windows of two days, one beginning every day."""
    found = events.run_to_end(events.windows(events.event_stream(spark, sf_dir), "2 days", "1 day"), "complete")
    return found.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")
