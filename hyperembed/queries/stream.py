"""Streaming queries: each stream is drained and compared with the batch result in SQL. SURVEY 2.16."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..session import work_folder
from ..streaming import events as ev
from .common import Registry

_reg = Registry()
add, verdict = _reg.add, _reg.verdict
QUERIES, ORACLES = _reg.queries, _reg.oracles


@add("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, event_type, count(DISTINCT user_id) AS members, count(*) AS events FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return ev.drain(ev.members_per_window(ev.event_stream(spark, sf_dir)))


@add("""WITH s AS (SELECT *, unnest([date_trunc('day', ts) + to_hours(h) FOR h IN [-12, 0, 12]]) AS start FROM events)
        SELECT strftime(start, '%Y-%m-%d %H:%M') AS start, event_type, count(DISTINCT user_id) AS members, count(*) AS events FROM s WHERE start <= ts AND ts < start + INTERVAL 1 DAY GROUP BY ALL""")
def stream_sliding(spark, sf_dir):
    return ev.drain(ev.members_per_window(ev.event_stream(spark, sf_dir), "1 day", "12 hours"))


@add("""WITH o AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM o)
        SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events, count(DISTINCT event_type) AS types FROM s GROUP BY user_id, n""")
def stream_session(spark, sf_dir):
    return ev.drain(ev.sessions(ev.event_stream(spark, sf_dir)))


@add("SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_dedup(spark, sf_dir):
    """Every event sent twice, counted once."""
    e = ev.event_stream(spark, sf_dir)
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    kept = ev.drain(ev.deduplicated(twice).select("event_id", "event_type"), "append")
    return kept.groupBy("event_type").agg(F.count("*").alias("n"))


@add("SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT user_id) AS size, count(*) AS events FROM events GROUP BY ALL")
def stream_degrees(spark, sf_dir):
    return ev.drain(ev.running_degrees(ev.event_stream(spark, sf_dir)), "update")


@add("SELECT event_type, round(sum(value * (user_id % 7)), 2) AS total FROM events GROUP BY event_type")
def stream_static_join(spark, sf_dir):
    """Each event weighed by a static vector of its user."""
    static = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("user_id").alias("id")).distinct().withColumn("vec", F.array((F.col("id") % 7).cast("double")))
    j = ev.joined_with(ev.event_stream(spark, sf_dir), static)
    return ev.drain(j.groupBy("event_type").agg(F.round(F.sum(F.col("value") * F.col("vec")[0]), 2).alias("total")))


@add("""SELECT 'node' AS side, CAST(user_id AS VARCHAR) AS id, count(*) AS total FROM events GROUP BY user_id
        UNION ALL SELECT 'edge', event_type || ' ' || strftime(ts, '%Y-%m-%d'), count(*) FROM events GROUP BY ALL UNION ALL SELECT 'all', '', count(*) FROM events""")
def stream_volumes(spark, sf_dir):
    return ev.running_volumes(ev.event_stream(spark, sf_dir), f"{work_folder(spark)}/volumes-{uuid.uuid4().hex}")
