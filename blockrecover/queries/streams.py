"""Streams over the events and image tables; their final results equal those of batch SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from .. import streaming
from ..session import shared_dir
from .lanes import lane, sql_lane

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


def _events(spark, sf_dir):
    return streaming.file_stream(spark, sf_dir, "events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def _plain(df):
    """Times without a zone, as the tables hold them (the session's zone cancels out)."""
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def str_tumbling(spark, sf_dir):
    return _plain(streaming.drain(streaming.tumbling(_events(spark, sf_dir), "1 hour"), mode="complete"))


@query("SELECT time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(CAST(15 * k AS INTEGER)) AS start, event_type, count(*) AS n FROM events, unnest(range(4)) AS u(k) GROUP BY 1, 2")
def str_sliding(spark, sf_dir):
    return _plain(streaming.drain(streaming.tumbling(_events(spark, sf_dir), "1 hour", "15 minutes"), mode="complete"))


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def str_session(spark, sf_dir):
    return _plain(streaming.drain(streaming.sessions(_events(spark, sf_dir), "30 minutes"), mode="complete"))


@query("SELECT DISTINCT event_id, event_type FROM events")
def str_dedup(spark, sf_dir):
    e = _events(spark, sf_dir)
    return streaming.drain(streaming.distinct_events(e).select("event_id", "event_type"))


@query("SELECT event_type, count(*) AS n FROM events WHERE event_type IN ('error', 'purchase') GROUP BY 1")
def str_static_join(spark, sf_dir):
    names = spark.createDataFrame([("error",), ("purchase",)], "event_type string")
    got = _events(spark, sf_dir).join(F.broadcast(names), "event_type").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return streaming.drain(got, mode="complete")


@query(f"WITH {sql_lane('gap')} SELECT CASE WHEN starts_with(payload, '~H1:') THEN 'header' ELSE 'footer' END AS kind, count(*) AS n FROM image WHERE starts_with(payload, '~H1:') OR contains(payload, '~E1:') GROUP BY 1")
def str_image(spark, sf_dir):
    """The image arrives as one file per chunk of blocks."""
    folder = f"{shared_dir(spark)}/chunks-{uuid.uuid4().hex}"
    lane(spark, sf_dir, "gap")[0].repartitionByRange(16, "pos").write.parquet(folder)
    return streaming.drain(streaming.sightings(streaming.file_stream(spark, folder)), mode="complete")


@query("""SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR
    WHERE a.event_type = 'error' AND b.event_type = 'purchase'""")
def str_interval_join(spark, sf_dir):
    e = _events(spark, sf_dir)
    return streaming.drain(streaming.followed(e.where("event_type = 'error'"), _events(spark, sf_dir).where("event_type = 'purchase'"), "1 hour"))
