"""Queries over streams: each runs its stream to the end of a file source, then reads what it wrote."""

from __future__ import annotations

from ..streaming import streams as S
from .registry import query
from ..sources import carriers as C

_TUMBLE = f"WITH {C.NATIVE_SQL} SELECT vehicle_id, epoch_s // 86400 * 86400 AS win_start, count(*) AS n, round(avg(sqrt(x*x + y*y + z*z)), 6) AS mag_mean FROM na GROUP BY 1, 2"


@query("streaming_summary", f"SELECT * FROM ({_TUMBLE}) WHERE win_start + 86400 <= (SELECT max(CAST(floor(epoch(ts)) AS BIGINT)) FROM events) - 3600")
def streaming_summary(spark, d):
    return S.summary(spark, d)


@query("stream_sliding")
def stream_sliding(spark, d):
    return S.sliding(spark, d)


@query("stream_session")
def stream_session(spark, d):
    return S.sessions(spark, d)


@query("stream_dedup", "SELECT count(*) AS events FROM events")
def stream_dedup(spark, d):
    return S.dedup(spark, d)


@query("stream_late_rows")
def stream_late_rows(spark, d):
    return S.late_rows(spark, d)


@query("stream_static_assign")
def stream_static_assign(spark, d):
    return S.static_assign(spark, d)


@query("stream_stream_fix_join", f"WITH {C.EVENTS_SQL} SELECT count(*) AS pairs FROM ev s JOIN ev f ON s.vehicle_id = f.vehicle_id AND abs(s.epoch_s - f.epoch_s) <= 1 WHERE f.event_type <> 'error'")
def stream_stream_fix_join(spark, d):
    return S.fix_join(spark, d)


@query("stream_restart", "SELECT count(*) AS events, count(DISTINCT event_id) AS distinct_events FROM events")
def stream_restart(spark, d):
    return S.restart(spark, d)


@query("stream_open_dwell")
def stream_open_dwell(spark, d):
    return S.open_dwell(spark, d)


@query("stream_drift_monitor")
def stream_drift_monitor(spark, d):
    return S.drift_monitor(spark, d)


@query("sink_upsert", "SELECT user_id AS vehicle_id, max(event_id) AS event_id FROM events GROUP BY 1")
def sink_upsert(spark, d):
    return S.upsert(spark, d)


@query("buffered_ingest", "SELECT count(*) AS events FROM events")
def buffered_ingest(spark, d):
    return S.ingest(spark, d)
