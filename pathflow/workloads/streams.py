"""Streaming workloads (extensions): each drains the events table and equals its batch twin."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..streaming import events as s
from .graphs import Graphs
from .registry import query
from .walks import LIKES, key


def _stream(g: Graphs) -> DataFrame:
    return s.read_stream(g.spark, g.sf_dir, "events.parquet")


def _clock(column: str):
    return F.date_format(column, "yyyy-MM-dd HH:mm:ss")


# the watermark holds the last windows back; what it emits is final
CLOSED = "(SELECT max(ts) FROM events) - INTERVAL 10 MINUTE"


@query(f"SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, event_type, edges FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS edges FROM events GROUP BY 1, 2) WHERE start + INTERVAL 1 HOUR <= {CLOSED}")
def stream_tumbling(g: Graphs) -> DataFrame:
    return s.drain(s.tumbling(_stream(g))).select(_clock("start").alias("start"), "event_type", "edges")


@query(f"SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS edges FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) - i * INTERVAL 1 HOUR AS start FROM events, range(0, 2) r(i)) WHERE start + INTERVAL 2 HOUR <= {CLOSED} GROUP BY 1")
def stream_sliding(g: Graphs) -> DataFrame:
    return s.drain(s.sliding(_stream(g))).select(_clock("start").alias("start"), "edges")


@query(
    f"""WITH g AS (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR > ts THEN 0 ELSE 1 END AS fresh FROM events),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS edges FROM n GROUP BY user_id, k HAVING max(ts) + INTERVAL 2 HOUR <= {CLOSED}"""
)
def stream_session(g: Graphs) -> DataFrame:
    return s.drain(s.sessions(_stream(g))).select("user_id", _clock("start").alias("start"), "edges")


@query("SELECT event_id, event_type FROM events")
def stream_dedup(g: Graphs) -> DataFrame:
    """Every event arrives twice; one of each stays."""
    twice = _stream(g).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return s.drain(s.deduplicated(twice).select("event_id", "event_type"))


@query(f"WITH {LIKES} SELECT event_id, dst AS part FROM events JOIN likes ON src = user_id")
def stream_static_hop(g: Graphs) -> DataFrame:
    """Every event takes the hop."""
    edges = g.commerce().edges("likes").select(key("src").alias("src"), key("dst").alias("dst"))
    return s.drain(s.static_hop(_stream(g), edges))


@query("SELECT v.event_id AS a, p.event_id AS b FROM events v JOIN events p ON p.user_id = v.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def stream_interval_join(g: Graphs) -> DataFrame:
    return s.drain(s.interval_join(_stream(g)))


@query("SELECT user_id, event_type, count(*) AS edges FROM events GROUP BY 1, 2")
def stream_stateful_shares(g: Graphs) -> DataFrame:
    """Counts of parallel edges per user and type, kept in state: what the taste walk multiplies."""
    return s.latest(s.drain(s.kept_counts(_stream(g)), "update"), ["user_id", "event_type"])


@query("SELECT a.user_id AS a, b.user_id AS b, count(*) AS shared FROM events a JOIN events b ON b.event_type = a.event_type AND date_trunc('hour', b.ts) = date_trunc('hour', a.ts) AND a.user_id < b.user_id GROUP BY 1, 2")
def stream_shared_counts(g: Graphs) -> DataFrame:
    """People who do the same in the same hour: changes of shared counts batch by batch, stored as products of lists of people and added up by pair at the end.
    As the stream makes no pairs, a resource is one block."""
    edges = _stream(g).withColumn("hour", F.date_trunc("hour", "ts"))
    with s.rocksdb(g.spark):
        changes = s.drain(s.shared_products(edges, ["event_type", "hour"], blocks=1))
    return s.shared_totals(changes)


@query(f"SELECT sum(edges)::BIGINT AS edges, count(*) AS windows FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS edges FROM events GROUP BY 1, 2) WHERE start + INTERVAL 1 HOUR <= {CLOSED}")
def stream_late_drop(g: Graphs) -> DataFrame:
    """A later file brings the first day again, after the watermark has passed it: its windows do not change."""
    e = g.table("events")
    folder = s.in_files(g.spark, e, [lambda d: d, lambda d: d.limit(0), lambda d: d.where("ts < timestamp_ntz '2024-01-02'"), lambda d: d.limit(0)])
    counted = s.drain(s.tumbling(s.read_stream(g.spark, folder, files_a_batch=1)))
    return counted.agg(F.sum("edges").alias("edges"), F.count("*").alias("windows"))
