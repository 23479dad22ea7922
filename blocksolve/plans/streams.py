"""Queries that run a stream to its end, with the SQL of the batch that they must equal."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from blocksolve.plans.blocks import rounded
from blocksolve.sources.store import shared_dir
from blocksolve.streaming import arrivals

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None):
    def add(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return add


@query("stream_tumbling", "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1")
def _(spark, d):
    return rounded(arrivals.drain(arrivals.tumbling(arrivals.event_stream(spark, d)), "complete"), "total")


@query("stream_sliding", "SELECT date_trunc('hour', ts)::TIMESTAMP - k * INTERVAL 1 HOUR AS start, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events, range(0, 6) r(k) GROUP BY 1")
def _(spark, d):
    return rounded(arrivals.drain(arrivals.tumbling(arrivals.event_stream(spark, d), "6 hours", "1 hour"), "complete"), "total")


@query(
    "stream_sessions",
    """WITH g AS (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts > p + INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s
      FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events))
    SELECT user_id, min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 12 HOUR)::TIMESTAMP AS stop, count(*) AS n FROM g GROUP BY user_id, s""",
)
def _(spark, d):
    return arrivals.drain(arrivals.sessions(arrivals.event_stream(spark, d)), "complete")


@query("stream_interval_join", "SELECT a.event_id AS a, b.event_id AS b, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def _(spark, d):
    return arrivals.drain(arrivals.purchases_after_views(arrivals.event_stream(spark, d)))


@query("stream_static_join", "SELECT event_id, event_type, length(event_type)::INT AS label FROM events")
def _(spark, d):
    labels = spark.read.parquet(f"{d}/events.parquet").select("event_type").distinct().withColumn("label", F.length("event_type"))
    return arrivals.drain(arrivals.labelled(arrivals.event_stream(spark, d), labels))


@query("stream_dedup", "SELECT DISTINCT event_id FROM events")
def _(spark, d):
    return arrivals.drain(arrivals.deduplicated(arrivals.event_stream(spark, d))).select("event_id")


@query("stream_counters", "SELECT (user_id % 8)::INT AS rb, count(*) AS visits, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1")
def _(spark, d):
    return rounded(arrivals.drain(arrivals.counters(arrivals.event_stream(spark, d)), "update", ["rb"]), "total")


@query("stream_counters_by_turns", SQL["stream_counters"])
def _(spark, d):
    """The same over several micro-batches: the last version of each counter."""
    turns = ["event_id % 3 = 0", "event_id % 3 = 1", "event_id % 3 = 2"]
    stream = arrivals.in_turns(spark.read.schema(arrivals.EVENTS).parquet(f"{d}/events.parquet"), turns, _place(spark))
    return rounded(arrivals.drain(arrivals.counters(stream), "update", ["rb"]), "total")


@query(
    "stream_late_rows",
    """SELECT * FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1)
    WHERE start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 2 HOUR""",
)
def _(spark, d):
    """Days in order, then all of the first days again: they are late, their windows are closed, and nothing of them is counted twice.
    The last window is still open."""
    turns = ["dayofmonth(ts) <= 10", "dayofmonth(ts) BETWEEN 11 AND 20", "dayofmonth(ts) > 20", "dayofmonth(ts) <= 5"]
    stream = arrivals.in_turns(spark.read.schema(arrivals.EVENTS).parquet(f"{d}/events.parquet"), turns, _place(spark))
    return rounded(arrivals.drain(arrivals.tumbling(stream)), "total")


def _place(spark) -> str:
    return f"{shared_dir(spark)}/turns-{uuid.uuid4().hex}"
