"""Queries of the lake and of data quality: layouts, round trips, retention, filters, duplicates, noise."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions import edge, geo
from ..plans.store import LABELLED_SQL, labelled_windows, shared_dir, summaries
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"


def lake_write(df, path: str, fmt: str = "parquet", buckets: int = 8, compression: str | None = None) -> None:
    """Date and hashed vehicle bucket as folders; a vehicle itself would make too many."""
    laid = df.withColumn("vehicle_bucket", F.pmod(F.xxhash64("vehicle_id"), F.lit(buckets)).cast("int"))
    w = laid.repartition("event_date", "vehicle_bucket").write.partitionBy("event_date", "vehicle_bucket").format(fmt)
    (w.option("compression", compression) if compression else w).save(path)


def lake_read(spark, path: str, schema, fmt: str = "parquet"):
    """Schema on read; broken JSON rows keep their text in _corrupt."""
    r = spark.read.schema(schema).format(fmt)
    return (r.option("columnNameOfCorruptRecord", "_corrupt") if fmt == "json" else r).load(path)


def _dated(spark, d):
    return summaries(spark, d).withColumn("event_date", F.date_from_unix_date(F.floor(F.col("win_start") / 86400).cast("int")))


_COUNTS = f"WITH {C.SUMMARY_SQL} SELECT CAST(make_timestamp(win_start * 1000000) AS DATE) AS event_date, count(*) AS windows, CAST(sum(n) AS BIGINT) AS samples FROM su GROUP BY 1"


def _counts(df):
    return df.groupBy("event_date").agg(F.count(F.lit(1)).alias("windows"), F.sum("n").cast("long").alias("samples"))


@query("lake_write", _COUNTS)
def lake_write_query(spark, d):
    path = f"{shared_dir(spark)}/lake-{uuid.uuid4().hex}"
    lake_write(_dated(spark, d), path)
    return _counts(spark.read.parquet(path))


_JSON = "vehicle_id long, win_start long, n long, mag_mean double, mag_var double, _corrupt string, event_date date"


@query("lake_read_json", _COUNTS)
def lake_read_json(spark, d):
    path = f"{shared_dir(spark)}/lake-{uuid.uuid4().hex}"
    lake_write(_dated(spark, d).select("vehicle_id", "win_start", "n", "mag_mean", "mag_var", "event_date"), path, "json")
    return _counts(lake_read(spark, path, _JSON, "json").where("_corrupt is null"))


@query("json_compression", _COUNTS)
def json_compression(spark, d):
    path = f"{shared_dir(spark)}/lake-{uuid.uuid4().hex}"
    lake_write(_dated(spark, d).select("vehicle_id", "win_start", "n", "mag_mean", "mag_var", "event_date"), path, "json", compression="gzip")
    return _counts(lake_read(spark, path, _JSON, "json").where("_corrupt is null"))


def retention_tier(age_days):
    """hot up to a week, warm up to three, then archive."""
    return F.when(age_days <= 7, "hot").when(age_days <= 21, "warm").otherwise("archive")


@query("retention_policy", f"WITH {C.EVENTS_SQL}, a AS (SELECT datediff('day', CAST(ts AS DATE), DATE '2024-01-31') AS age FROM ev) SELECT CASE WHEN age <= 7 THEN 'hot' WHEN age <= 21 THEN 'warm' ELSE 'archive' END AS tier, count(*) AS events FROM a GROUP BY 1")
def retention_policy(spark, d):
    age = F.datediff(F.lit("2024-01-31").cast("date"), F.col("ts").cast("date"))
    return C.events(spark, d).groupBy(retention_tier(age).alias("tier")).agg(F.count(F.lit(1)).alias("events"))


@query("fix_quality_filter", "SELECT user_id AS vehicle_id, count(*) AS good_fixes FROM events WHERE event_type <> 'error' GROUP BY 1")
def fix_quality_filter(spark, d):
    return C.fixes(spark, d).where("quality >= 1").groupBy("vehicle_id").agg(F.count(F.lit(1)).alias("good_fixes"))


@query("dedup_events", "SELECT count(*) AS events, CAST(sum(event_id) AS BIGINT) AS ids FROM (SELECT DISTINCT event_id FROM (SELECT event_id FROM events UNION ALL SELECT event_id FROM events WHERE event_id % 7 = 0))")
def dedup_events(spark, d):
    """Packets sent twice are dropped by event_id."""
    e = C.events(spark, d)
    return e.unionByName(e.where("event_id % 7 = 0")).dropDuplicates(["event_id"]).agg(F.count(F.lit(1)).alias("events"), F.sum("event_id").alias("ids"))


@query("position_noise", f"{L}, sp AS (SELECT event_id, landmark_m, {C.HAVERSINE_SQL.format(a_lat='lag(lat) OVER w', a_lon='lag(lon) OVER w', b_lat='lat', b_lon='lon')} / (win_start - lag(win_start) OVER w) AS speed FROM lw WINDOW w AS (PARTITION BY vehicle_id ORDER BY win_start, event_id)) SELECT count(*) AS windows, count(*) FILTER (landmark_m > 150) AS off_route, count(*) FILTER (speed > 30) AS too_fast FROM sp")
def position_noise(spark, d):
    s = geo.speed(labelled_windows(spark, d).withColumn("epoch_s", F.col("win_start")))
    return s.agg(F.count(F.lit(1)).alias("windows"), F.count_if(F.col("landmark_m") > 150).alias("off_route"), F.count_if(F.col("speed") > 30).alias("too_fast"))


@query("index_lookup", f"{L} SELECT landmark_id, label, count(*) AS windows FROM lw WHERE event_date BETWEEN DATE '2024-01-08' AND DATE '2024-01-14' AND label IN ('Aggressive', 'Very Aggressive') AND landmark_id < 10 GROUP BY 1, 2")
def index_lookup(spark, d):
    """A slice by date folders, place and behaviour; all three reach the scan."""
    w = labelled_windows(spark, d).where("event_date between date'2024-01-08' and date'2024-01-14'").where(F.col("label").isin("Aggressive", "Very Aggressive") & (F.col("landmark_id") < 10))
    return w.groupBy("landmark_id", "label").agg(F.count(F.lit(1)).alias("windows"))


@query("alignment_snap", f"{L} SELECT event_id, landmark_id, round(lm.lat, 6) AS snapped_lat, round(lm.lon, 6) AS snapped_lon, round(landmark_m, 4) AS moved_m FROM lw JOIN lm USING (landmark_id)")
def alignment_snap(spark, d):
    s = geo.snap(C.fixes(spark, d).join(summaries(spark, d).select("event_id"), "event_id", "left_semi"), C.landmarks(spark, d))
    return s.select("event_id", "landmark_id", F.round("snapped_lat", 6).alias("snapped_lat"), F.round("snapped_lon", 6).alias("snapped_lon"), F.round("landmark_m", 4).alias("moved_m"))


@query("packet_lake_roundtrip", f"WITH {C.SUMMARY_SQL} SELECT count(*) AS packets, CAST(sum(n) AS BIGINT) AS samples FROM su")
def packet_lake_roundtrip(spark, d):
    path = f"{shared_dir(spark)}/packets-{uuid.uuid4().hex}"
    edge.encode_packet(summaries(spark, d)).select("packet").write.text(path, compression="gzip")
    back = edge.decode_packet(spark.read.text(path).withColumnRenamed("value", "packet"))
    return back.agg(F.count("vehicle_id").alias("packets"), F.sum("n").alias("samples"))
