"""Queries that replay the events table as a stream; each equals its batch result."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from . import streaming
from .queries import M, query
from .sources import read, read_stream


def _events(spark, sf_dir: str, files: int = 4):
    """The events as a stream of several files in order of time."""
    from .storage import shared_folder

    folder = f"{shared_folder(spark)}/replay-{uuid.uuid4().hex}"
    rows = read(spark, sf_dir, "events")
    rows.repartitionByRange(files, "event_id").sortWithinPartitions("event_id").write.parquet(folder)
    return read_stream(spark, folder, rows.schema, files)


def _finished(df, mode: str = "complete"):
    return streaming.finish(df, f"s{uuid.uuid4().hex}", mode)[0]


@query("stream_matrix", f"SELECT CAST(user_id AS VARCHAR) AS block_key, CAST(event_id % {M} AS INT) AS part_ix, count(*) AS n FROM events GROUP BY ALL")
def stream_matrix(spark, sf_dir):
    return _finished(streaming.matrix(_events(spark, sf_dir), F.col("user_id").cast("string"), F.pmod("event_id", F.lit(M))))


@query("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    counts = streaming.windowed(streaming.with_lateness(streaming.instants(_events(spark, sf_dir)), "1 hour"), ["event_type"])
    return _finished(counts.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n"))


@query("stream_sliding", "SELECT strftime(start, '%Y-%m-%d %H') AS start, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts) + INTERVAL 12 HOUR * h for h in [-1, 0, 1]]) AS start, ts FROM events) WHERE ts >= start AND ts < start + INTERVAL 1 DAY GROUP BY 1")
def stream_sliding(spark, sf_dir):
    counts = streaming.windowed(streaming.instants(_events(spark, sf_dir)), [], "sliding", "1 day", "12 hours")
    return _finished(counts.select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "n"))


_MOMENT = "strftime({}, '%Y-%m-%d %H:%M:%S.%f')"


@query("stream_sessions", f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g)
SELECT {_MOMENT.format('min(ts)')} AS start, {_MOMENT.format('max(ts) + INTERVAL 6 HOUR')} AS "end", user_id, count(*) AS n FROM s GROUP BY user_id, session""")
def stream_sessions(spark, sf_dir):
    late = streaming.with_lateness(streaming.instants(_events(spark, sf_dir)), "1 hour")
    moment = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS").alias(c)
    return _finished(streaming.windowed(late, ["user_id"], "session", gap="6 hours").select(moment("start"), moment("end"), "user_id", "n"))


@query("stream_dedup", "SELECT DISTINCT user_id, event_type, strftime(ts, '%Y-%m-%d') AS day FROM events")
def stream_dedup(spark, sf_dir):
    rows = streaming.with_lateness(streaming.instants(_events(spark, sf_dir)), "40 days")
    rows = rows.withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    return _finished(streaming.dedup(rows, ["user_id", "event_type", "day"]).select("user_id", "event_type", "day"), "append")


@query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    customers = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_name")
    return _finished(streaming.join_static(_events(spark, sf_dir), customers, ["user_id"]).select("event_id", "c_name"), "append")


@query("stream_interval_join", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def stream_interval_join(spark, sf_dir):
    rows = streaming.with_lateness(streaming.instants(_events(spark, sf_dir)), "1 hour")
    more = streaming.with_lateness(streaming.instants(_events(spark, sf_dir)), "1 hour")
    met = streaming.join_interval(rows.where("event_type = 'click'"), more.where("event_type = 'purchase'"), "user_id", "2 HOURS")
    return _finished(met.select(F.col("a.event_id").alias("click_id"), F.col("b.event_id").alias("purchase_id")), "append")


@query("stream_block_state", "SELECT CAST(user_id AS VARCHAR) AS block_key, count(*) AS records, count(*) * (count(*) - 1) // 2 AS pairs FROM events GROUP BY 1")
def stream_block_state(spark, sf_dir):
    rows = _events(spark, sf_dir).withColumn("block_key", F.col("user_id").cast("string"))
    states = _finished(streaming.block_state(rows), "update")
    return states.groupBy("block_key").agg(F.max("records").alias("records"), F.max("pairs").alias("pairs"))
