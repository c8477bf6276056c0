"""Queries of geography."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import geo
from ..plans.store import LABELLED_SQL, labelled_windows
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"
FL = f"WITH {C.FIX_SQL},{C.LANDMARK_SQL}"


@query("haversine", f"{FL} SELECT event_id, round({C.haversine_sql('fx', 'lm')}, 4) AS metres FROM fx JOIN lm ON lm.landmark_id = 0")
def haversine(spark, d):
    zero = C.landmarks(spark, d).where("landmark_id = 0").select(F.col("lat").alias("la"), F.col("lon").alias("lo"))
    return C.fixes(spark, d).crossJoin(F.broadcast(zero)).select("event_id", F.round(geo.haversine(F.col("lat"), F.col("lon"), F.col("la"), F.col("lo")), 4).alias("metres"))


_NEAR = f"{FL}, n AS (SELECT event_id, true_landmark, min({{'d': {C.haversine_sql('fx', 'lm')}, 'id': landmark_id, 'zone': zone}}) AS b FROM fx CROSS JOIN lm GROUP BY 1, 2) SELECT event_id, b.id AS landmark_id, round(b.d, 4) AS landmark_m, b.zone AS zone, b.id = true_landmark AS right_one FROM n"


def _near(df):
    return df.select("event_id", "landmark_id", F.round("landmark_m", 4).alias("landmark_m"), "zone", (F.col("landmark_id") == F.col("true_landmark")).alias("right_one"))


@query("nearest_landmark", _NEAR)
def nearest_landmark(spark, d):
    return _near(geo.nearest(C.fixes(spark, d), C.landmarks(spark, d)))


@query("nearest_landmark_grid", _NEAR)
def nearest_landmark_grid(spark, d):
    return _near(geo.nearest(C.fixes(spark, d), C.landmarks(spark, d), method="cells"))


@query("within_radius", f"{FL}, c AS (SELECT lat, lon FROM fx WHERE event_id = 17) SELECT fx.event_id, round({C.haversine_sql('c', 'fx')}, 4) AS distance_m FROM fx, c WHERE {C.haversine_sql('c', 'fx')} <= 100")
def within_radius(spark, d):
    f = C.fixes(spark, d)
    at = f.where("event_id = 17").first()
    return geo.within(f, at["lat"], at["lon"], 100.0).select("event_id", F.round("distance_m", 4).alias("distance_m"))


@query("radius_self_join", f"{FL} SELECT a.event_id AS a_id, count(*) AS neighbours FROM fx a JOIN fx b ON abs(a.lat - b.lat) < 0.001 AND a.event_id <> b.event_id AND {C.haversine_sql('a', 'b')} <= 100 GROUP BY 1")
def radius_self_join(spark, d):
    return geo.radius_counts(C.fixes(spark, d), 100.0).withColumnRenamed("event_id", "a_id")


@query("zone_rollup", f"{L} SELECT zone, place, count(*) AS windows FROM lw GROUP BY 1, 2")
def zone_rollup(spark, d):
    return labelled_windows(spark, d).groupBy("zone", "place").agg(F.count(F.lit(1)).alias("windows"))


@query("speed_between_fixes", f"{FL}, s AS (SELECT event_id, {C.HAVERSINE_SQL.format(a_lat='lag(lat) OVER w', a_lon='lag(lon) OVER w', b_lat='lat', b_lon='lon')} / nullif(epoch_s - lag(epoch_s) OVER w, 0) AS speed FROM fx WHERE quality = 1 WINDOW w AS (PARTITION BY vehicle_id ORDER BY epoch_s, event_id)) SELECT event_id, round(speed, 6) AS speed FROM s")
def speed_between_fixes(spark, d):
    return geo.speed(C.fixes(spark, d).where("quality = 1")).select("event_id", F.round("speed", 6).alias("speed"))
