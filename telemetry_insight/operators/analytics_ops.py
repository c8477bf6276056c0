"""Queries of the macro aggregations."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import analytics as A
from ..functions import edge, profiles as P
from ..plans.store import LABELLED_SQL, label_windows, labelled_windows, summaries
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"


def hotspot_sql(labels: tuple[str, ...], k: int = 3) -> str:
    inside = ", ".join(f"'{x}'" for x in labels)
    return f"{L}, h AS (SELECT * FROM lw WHERE quality = 1 AND label IN ({inside})) SELECT landmark_id, place, count(*) AS events, round(avg(instability), 6) AS mean_instability, (SELECT count(*) FROM h) AS total_events, (SELECT min(win_start) FROM h) AS first_window, (SELECT max(win_start) FROM h) AS last_window FROM h GROUP BY 1, 2 ORDER BY events DESC, landmark_id LIMIT {k}"


def _hot(w, labels=("Aggressive",), k=3):
    return A.hotspots(w, labels, k).withColumn("mean_instability", F.round("mean_instability", 6))


@query("aggressive_hotspots", hotspot_sql(("Aggressive",)))
def aggressive_hotspots(spark, d):
    return _hot(labelled_windows(spark, d))


@query("severe_hotspots", hotspot_sql(A.SEVERE))
def severe_hotspots(spark, d):
    return _hot(labelled_windows(spark, d), A.SEVERE)


@query("full_scan_query", hotspot_sql(("Aggressive",)))
def full_scan_query(spark, d):
    """The same answer from raw samples, without the index."""
    return _hot(label_windows(summaries(spark, d), P.VERSION_0, C.landmarks(spark, d)))


_STAYS = """, o AS (SELECT *, CASE WHEN lag(zone) OVER w = zone AND win_start - lag(win_start) OVER w <= {gap} THEN 0 ELSE 1 END AS new FROM lw {where} WINDOW w AS (PARTITION BY vehicle_id ORDER BY win_start, event_id)),
r AS (SELECT *, sum(new) OVER (PARTITION BY vehicle_id ORDER BY win_start, event_id) AS run FROM o),
st AS (SELECT vehicle_id, run, zone AS place, (max(win_start) + 3 - min(win_start)) / 60e0 AS minutes FROM r GROUP BY 1, 2, 3)
SELECT place, count(*) AS stays, round(sum(minutes), 4) AS minutes, round(max(minutes), 4) AS longest FROM st GROUP BY 1"""


def _dwell(df):
    return df.select("place", "stays", F.round("minutes", 4).alias("minutes"), F.round("longest", 4).alias("longest"))


@query("dwell_time", L + _STAYS.format(gap=43200, where=""))
def dwell_time(spark, d):
    return _dwell(A.dwell(labelled_windows(spark, d), 43200))


@query("dwell_low_motion", L + _STAYS.format(gap=43200, where="WHERE instability <= 0.35"))
def dwell_low_motion(spark, d):
    return _dwell(A.dwell(labelled_windows(spark, d), 43200, tau=0.35))


@query("dwell_sessions", f"WITH {C.NATIVE_SQL}, o AS (SELECT *, CASE WHEN epoch_s - lag(epoch_s) OVER w <= 21599 THEN 0 ELSE 1 END AS new FROM na WINDOW w AS (PARTITION BY vehicle_id ORDER BY epoch_s, event_id)), r AS (SELECT *, sum(new) OVER (PARTITION BY vehicle_id ORDER BY epoch_s, event_id) AS run FROM o) SELECT vehicle_id, min(epoch_s) AS first_s, count(*) AS samples FROM r GROUP BY vehicle_id, run")
def dwell_sessions(spark, d):
    """Activity sessions by session windows: gaps of under six hours belong together; a sample without a time is a session of its own.

    Session windows that touch are merged, so a window of 21599 s holds together gaps of up to 21599 s.
    """
    n = C.native(spark, d).select("vehicle_id", "epoch_s", F.timestamp_seconds("epoch_s").alias("at"))
    timed = n.groupBy("vehicle_id", F.session_window("at", "21599 seconds")).agg(F.min("epoch_s").alias("first_s"), F.count(F.lit(1)).alias("samples")).drop("session_window")
    return timed.union(n.where("epoch_s is null").select("vehicle_id", "epoch_s", F.lit(1).cast("long")))


@query("count_profile", f"{L} SELECT count(*) AS windows FROM lw WHERE label = 'Moderate'")
def count_profile(spark, d):
    return labelled_windows(spark, d).where("label = 'Moderate'").agg(F.count(F.lit(1)).alias("windows"))


_BAND = "CASE WHEN hour BETWEEN 6 AND 11 THEN 'morning' WHEN hour BETWEEN 17 AND 22 THEN 'evening' END"


@query("count_profile_cube", f"{L} SELECT label, zone, {_BAND} AS band, count(*) AS windows, CAST(grouping_id(label, zone, {_BAND}) AS BIGINT) AS level FROM lw WHERE {_BAND} IS NOT NULL GROUP BY CUBE (label, zone, {_BAND})")
def count_profile_cube(spark, d):
    w = labelled_windows(spark, d).withColumn("band", A.band(F.col("hour"))).where("band is not null")
    return w.cube("label", "zone", "band").agg(F.count(F.lit(1)).alias("windows"), F.grouping_id().alias("level"))


@query("route_efficiency", f"{L}, s AS (SELECT *, {C.HAVERSINE_SQL.format(a_lat='lag(lat) OVER w', a_lon='lag(lon) OVER w', b_lat='lat', b_lon='lon')} / nullif(win_start - lag(win_start) OVER w, 0) AS speed FROM lw WHERE quality = 1 WINDOW w AS (PARTITION BY vehicle_id ORDER BY win_start, event_id)) SELECT route, count(*) FILTER (hour BETWEEN 6 AND 11) AS morning_events, round(avg(instability) FILTER (hour BETWEEN 6 AND 11), 6) AS morning_instability, round(avg(speed) FILTER (hour BETWEEN 6 AND 11), 6) AS morning_speed, count(*) FILTER (hour BETWEEN 17 AND 22) AS evening_events, round(avg(instability) FILTER (hour BETWEEN 17 AND 22), 6) AS evening_instability, round(avg(speed) FILTER (hour BETWEEN 17 AND 22), 6) AS evening_speed FROM s GROUP BY route")
def route_efficiency(spark, d):
    c = A.compare_bands(labelled_windows(spark, d))
    return c.select("route", *[F.round(x, 6).alias(x) if "events" not in x else F.col(x) for b in ("morning", "evening") for x in (f"{b}_events", f"{b}_instability", f"{b}_speed")])


@query("spatial_patterns", f"{L}, c AS (SELECT lat, lon FROM lm WHERE landmark_id = 12), n AS (SELECT lw.* FROM lw, c WHERE {C.haversine_sql('c', 'lw')} <= 250) SELECT label, count(*) AS windows, round(avg(instability), 6) AS instability, round(avg(extreme), 6) AS extreme, round(count(*) / (SELECT count(*) FROM n), 6) AS share FROM n GROUP BY 1")
def spatial_patterns(spark, d):
    at = C.landmarks(spark, d).where("landmark_id = 12").first()
    r = A.around(labelled_windows(spark, d), at["lat"], at["lon"], 250.0)
    return r.select("label", "windows", *[F.round(c, 6).alias(c) for c in ("instability", "extreme", "share")])


@query("spatial_density", f"{L}, c AS (SELECT lat, lon FROM lm WHERE landmark_id = 12) SELECT lw.hour, count(*) AS windows, round(count(*) / (pi() * 0.0625e0), 4) AS per_km2 FROM lw, c WHERE {C.haversine_sql('c', 'lw')} <= 250 GROUP BY 1")
def spatial_density(spark, d):
    """Windows around a landmark by hour, and how many that is to the square kilometre."""
    at = C.landmarks(spark, d).where("landmark_id = 12").first()
    return A.density(labelled_windows(spark, d), at["lat"], at["lon"], 250.0).withColumn("per_km2", F.round("per_km2", 4))


_IDLE = """, o AS (SELECT *, CASE WHEN lag(route) OVER w = route AND win_start - lag(win_start) OVER w <= 43200 THEN 0 ELSE 1 END AS new FROM lw WHERE instability <= 0.35 WINDOW w AS (PARTITION BY vehicle_id ORDER BY win_start, event_id)),
r AS (SELECT *, sum(new) OVER (PARTITION BY vehicle_id ORDER BY win_start, event_id) AS run FROM o),
st AS (SELECT route, min(win_start) AS first, (max(win_start) + 3 - min(win_start)) / 60e0 AS minutes FROM r GROUP BY vehicle_id, run, route),
b AS (SELECT route, minutes, CAST(floor(first % 86400 / 3600e0) AS INTEGER) AS h FROM st)
SELECT route, round(coalesce(sum(minutes) FILTER (h BETWEEN 6 AND 11), 0), 4) AS morning_idle, round(coalesce(sum(minutes) FILTER (h BETWEEN 17 AND 22), 0), 4) AS evening_idle, round(coalesce(sum(minutes) FILTER (h BETWEEN 17 AND 22), 0) - coalesce(sum(minutes) FILTER (h BETWEEN 6 AND 11), 0), 4) AS idle_change FROM b GROUP BY route"""


@query("route_idle", L + _IDLE)
def route_idle(spark, d):
    """Minutes of low-motion stays that start in the morning and in the evening, by route, and the difference."""
    return A.idle_bands(labelled_windows(spark, d), 43200, 0.35).select("route", *[F.round(c, 4).alias(c) for c in ("morning_idle", "evening_idle", "idle_change")])


@query("anomaly_windows", f"{L}, q AS (SELECT quantile_cont(instability, 0.99) AS qi, quantile_cont(extreme, 0.99) AS qe FROM lw) SELECT event_id, label, instability > qi AS by_instability, extreme > qe AS by_extreme FROM lw, q WHERE instability > qi OR extreme > qe")
def anomaly_windows(spark, d):
    w = labelled_windows(spark, d)
    q = w.agg(F.percentile("instability", 0.99).alias("qi"), F.percentile("extreme", 0.99).alias("qe"))
    i, e = F.col("instability") > F.col("qi"), F.col("extreme") > F.col("qe")
    return w.crossJoin(F.broadcast(q)).where(i | e).select("event_id", "label", i.alias("by_instability"), e.alias("by_extreme"))


@query("persona_reports", f"{L} SELECT 'planner' AS persona, 'route ' || route AS subject, count(*) AS windows, round(avg(instability), 6) AS value FROM lw GROUP BY route UNION ALL SELECT 'safety', place, count(*), round(avg(extreme), 6) FROM lw WHERE label IN ('Aggressive', 'Very Aggressive') GROUP BY place UNION ALL SELECT 'fleet', 'vehicle ' || vehicle_id, count(*), round(max(extreme), 6) FROM lw GROUP BY vehicle_id")
def persona_reports(spark, d):
    w = labelled_windows(spark, d)
    n = F.count(F.lit(1)).alias("windows")
    planner = w.groupBy(F.concat(F.lit("route "), F.col("route")).alias("subject")).agg(n, F.round(F.avg("instability"), 6).alias("value")).select(F.lit("planner").alias("persona"), "*")
    safety = w.where(F.col("label").isin(*A.SEVERE)).groupBy(F.col("place").alias("subject")).agg(n, F.round(F.avg("extreme"), 6).alias("value")).select(F.lit("safety").alias("persona"), "*")
    fleet = w.groupBy(F.concat(F.lit("vehicle "), F.col("vehicle_id")).alias("subject")).agg(n, F.round(F.max("extreme"), 6).alias("value")).select(F.lit("fleet").alias("persona"), "*")
    return planner.unionByName(safety).unionByName(fleet)


@query("hourly_rollup", f"{L} SELECT label, landmark_id, hour, count(*) AS windows, round(sum(instability), 6) AS sum_instability FROM lw GROUP BY 1, 2, 3")
def hourly_rollup(spark, d):
    """The roll-up from which hotspots, counts and band comparisons can be answered exactly."""
    return labelled_windows(spark, d).groupBy("label", "landmark_id", "hour").agg(F.count(F.lit(1)).alias("windows"), F.round(F.sum("instability"), 6).alias("sum_instability"))


@query("feature_preservation", f"WITH {C.SUMMARY_SQL} SELECT count(*) AS windows, 1e0 AS agreement FROM su")
def feature_preservation(spark, d):
    """Share of windows whose label from the summary equals the label worked out from raw samples."""
    raw = C.burst(spark, d).groupBy("vehicle_id", "win_start").agg(*[F.percentile(a, 0.99).alias(f"{a}_p99") for a in "xyz"], F.var_pop(edge.magnitude(F.col("x"), F.col("y"), F.col("z"))).alias("instability"))
    again = P.assign(raw.withColumn("extreme", edge.extreme()), P.VERSION_0).select("vehicle_id", "win_start", F.col("label").alias("raw_label"))
    both = labelled_windows(spark, d).join(again, ["vehicle_id", "win_start"])
    return both.agg(F.count(F.lit(1)).alias("windows"), F.avg((F.col("label") == F.col("raw_label")).cast("double")).alias("agreement"))
