"""Streams over the events table; each equals a batch query once its input is drained."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load_table
from ..streaming import events as ev

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):  # noqa: ANN201
    def add(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _told(df: DataFrame) -> DataFrame:
    """Times as text, so that zones cannot differ."""
    return df.withColumns({c: F.date_format(c, "yyyy-MM-dd HH:mm:ss") for c in ("start", "end")})


_T = "strftime({}, '%Y-%m-%d %H:%M:%S')"
query("stream_tumbling", f"SELECT {_T.format('a')} AS \"start\", {_T.format('a + INTERVAL 1 DAY')} AS \"end\", event_type, count(*) AS n FROM (SELECT date_trunc('day', ts) AS a, event_type FROM events) GROUP BY a, event_type")(lambda s, d: _told(ev.drain(ev.windowed(ev.source(s, d)), "complete")))
query("stream_sliding", f"SELECT {_T.format('a')} AS \"start\", {_T.format('a + INTERVAL 1 DAY')} AS \"end\", event_type, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '1970-01-01') - to_hours(6 * k) AS a, event_type FROM events, range(4) t(k)) GROUP BY a, event_type")(lambda s, d: _told(ev.drain(ev.windowed(ev.source(s, d), "sliding"), "complete")))
query(
    "stream_session",
    f"SELECT {_T.format('min(ts)')} AS \"start\", {_T.format('max(ts) + INTERVAL 30 MINUTES')} AS \"end\", user_id, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, g",
)(lambda s, d: _told(ev.drain_sessions(ev.source(s, d))))
query("stream_dedup_watermark", "SELECT DISTINCT user_id, event_type FROM events")(lambda s, d: ev.drain(ev.first_seen_links(ev.source(s, d))).select("user_id", "event_type"))
query("stream_static_join", "SELECT event_id, 'kind_' || event_type AS p, 'Event' AS concept, user_id FROM events")(
    lambda s, d: ev.drain(ev.join_static(ev.source(s, d), load_table(s, d, "events", ["event_type"]).distinct().select("event_type", F.concat(F.lit("kind_"), "event_type").alias("p"), F.lit("Event").alias("concept"))))
)
query("stream_interval_join", "SELECT a.user_id, a.event_id AS error_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error' AND b.event_type = 'purchase'")(lambda s, d: ev.drain(ev.join_interval(ev.source(s, d))))
query("stream_stateful_degree", "SELECT event_type, count(DISTINCT user_id) AS degree FROM events GROUP BY event_type")(lambda s, d: ev.drain(ev.running_degree(ev.source(s, d)), "update").groupBy("event_type").agg(F.max("degree").alias("degree")))


@query("stream_late_rows", f"""WITH e AS (SELECT event_id, CAST(ts AS TIMESTAMP) AS ts FROM events), m AS (SELECT epoch_us(min(ts)) + (epoch_us(max(ts)) - epoch_us(min(ts))) // 2 AS cut FROM e), w AS (SELECT max(ts) AS last FROM e, m WHERE epoch_us(ts) <= cut AND event_id % 10 <> 0)
SELECT 'kept' AS policy, count(*) AS n FROM e UNION ALL SELECT 'dropped', count(*) FROM e, m, w WHERE NOT (event_id % 10 = 0 AND epoch_us(ts) <= cut AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= last - INTERVAL '{ev.LATENESS}')""")
def late(s: SparkSession, d: str) -> DataFrame:
    """The table's rows in three batches, a tenth of the first half in time last: how many of all rows are counted with late ones dropped, and kept.

    Rows of a batch are late by the watermark that the batch before went by, so those of the third by the first one's latest time.
    """
    rows = load_table(s, d, "events", ["event_id", "ts"])
    first, last = rows.agg(F.min(F.unix_micros(F.col("ts").cast("timestamp"))), F.max(F.unix_micros(F.col("ts").cast("timestamp")))).first()
    cut = first + (last - first) // 2 if first is not None else 0
    late_rows = F.col("event_id") % 10 == 0
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return ev.late_policy(s, rows.select(F.when((us <= cut) & ~late_rows, 1).when(us > cut, 2).otherwise(3).alias("batch"), F.col("ts").cast("timestamp").alias("ts")))
