"""Streaming queries: each runs a stream over files to its end and returns what it wrote."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import dedup
from ..sources.pages import shared_path
from ..streaming import curate, telemetry
from .common import shard, sql_kept, table


def _events(spark, sf):
    path = shared_path(spark, "events")
    table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type", "value", "props").repartitionByRange(3, "ts").write.parquet(path)
    return telemetry.event_stream(spark, path)


def _time(c):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias("start")


def s_incremental_dedup(spark, sf):
    """Five arrivals of four shards each, in order of shards."""
    root = shared_path(spark, "shards")
    docs = table(spark, sf, "documents").select("doc_id", shard().alias("shard_id"), "text")
    for i in range(5):
        docs.where(F.floor(F.col("shard_id") / 4) == i).coalesce(1).write.mode("append").parquet(root)
    runner = curate.IncrementalDedup(spark).run(curate.shard_stream(spark, root, "doc_id long, shard_id int, text string"))
    return dedup.decoded(runner.survivors(spark))


def s_tumbling(spark, sf):
    w = telemetry.collect_stream(telemetry.tumbling(_events(spark, sf)), "complete")
    return w.select(_time("start"), "event_type", "n", F.round("total", 3).alias("total"))


def s_sliding(spark, sf):
    return telemetry.collect_stream(telemetry.sliding(_events(spark, sf)), "complete").select(_time("start"), "n")


def s_session(spark, sf):
    return telemetry.collect_stream(telemetry.sessions(_events(spark, sf)), "complete").select("user_id", _time("start"), "n")


def s_dedup_watermark(spark, sf):
    rows = telemetry.collect_stream(telemetry.first_of_key(_events(spark, sf), ["user_id", "event_type"]))
    return rows.select("user_id", "event_type")


def s_stream_static(spark, sf):
    weights = spark.createDataFrame([("view", 1), ("purchase", 5)], "event_type string, weight int")
    return telemetry.collect_stream(telemetry.with_static(_events(spark, sf), weights, "event_type").select("event_id", "weight"))


def s_stream_stream(spark, sf):
    return telemetry.collect_stream(telemetry.interval_pairs(_events(spark, sf), "view", "purchase"))


def s_state(spark, sf):
    rows = telemetry.collect_stream(telemetry.running_first(_events(spark, sf)), "update")
    return rows.groupBy("user_id").agg(F.max("n").alias("n"))


CALLS = {f.__name__: f for f in (s_incremental_dedup, s_tumbling, s_sliding, s_session, s_dedup_watermark, s_stream_static, s_stream_stream, s_state)}

ORACLES = {
    "s_incremental_dedup": f"WITH {sql_kept('1')} SELECT doc_id, shard_id, para_no FROM ranked WHERE nth = 1",
    "s_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY 1, 2",
    "s_sliding": """
WITH w AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS s FROM events), b AS (SELECT s FROM w UNION ALL SELECT s - INTERVAL 30 MINUTE FROM w)
SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM b GROUP BY 1""",
    "s_session": """
WITH g AS (SELECT user_id, ts, (lag(ts) OVER w IS NULL OR ts > lag(ts) OVER w + INTERVAL 30 MINUTE)::INTEGER AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, no""",
    "s_dedup_watermark": "SELECT DISTINCT user_id, event_type FROM events",
    "s_stream_static": "SELECT event_id, CASE event_type WHEN 'view' THEN 1 ELSE 5 END::INTEGER AS weight FROM events WHERE event_type IN ('view', 'purchase')",
    "s_stream_stream": """SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR""",
    "s_state": "SELECT user_id, count(*) AS n FROM events GROUP BY user_id",
}
