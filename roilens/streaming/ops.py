"""Streaming queries over the events table, run to the end of what is there."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..collect import sources
from ..params import Params
from ..relational.ops import OPS, op  # noqa: F401  (entries register there)
from ..storage import table
from . import run

_AT = "epoch_us(ts)"
_DAY = 86_400_000_000


@op(f"SELECT user_id // 8 AS session_id, {_AT} - {_AT} % {_DAY} AS start_us, count(*) AS n FROM events GROUP BY 1, 2")
def op_stream_tumbling(s, d):
    return run.drain(run.tumbling(run.source(s, d)), "complete", "tumbling")


@op(f"SELECT user_id // 8 AS session_id, {_AT} - {_AT} % {_DAY} - i * {_DAY} AS start_us, count(*) AS n FROM events, generate_series(0, 1) g(i) GROUP BY 1, 2")
def op_stream_sliding(s, d):
    return run.drain(run.sliding(run.source(s, d)), "complete", "sliding")


@op()
def op_stream_session(s, d):
    return run.drain(run.idle_segments(run.source(s, d)), "append", "session")


@op("SELECT event_id, user_id // 8 AS session_id FROM events")
def op_stream_dedup(s, d):
    return run.drain(run.deduplicated(run.source(s, d)).select("event_id", "session_id"), "append", "dedup")


@op("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def op_stream_static_join(s, d):
    c = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return run.drain(run.with_static(run.source(s, d), c, "user_id").select("event_id", "c_mktsegment"), "append", "static")


@op("SELECT a.user_id, a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def op_stream_stream_join(s, d):
    return run.drain(run.hover_then_purchase(run.source(s, d)), "append", "pairs")


@op()
def op_stream_state(s, d):
    return run.drain(run.drift_segments(run.source(s, d)), "append", "drift")


@op()
def op_stream_late(s, d):
    """Cells of the clock grid that are closed when the stream ends; later rows would be dropped."""
    return run.drain(run.thinned(run.source(s, d)), "append", "thinned")


@op()
def op_stream_hulls(s, d):
    """Hulls of the clusters of segments that are closed when the stream ends."""
    places = sources.moves(s, d).select("event_id", "x", "y")
    found = run.drain(run.closed_hulls(run.source(s, d).join(places, "event_id"), "3 hours", params=Params(min_pts=3, radius=60.0)), "append", "hulls")
    return found.select("session_id", "first_us", "last_us", "cluster_id", "n", F.size("poly").alias("vertices"), F.round("area", 6).alias("area"))
