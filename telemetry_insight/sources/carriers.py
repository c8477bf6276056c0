"""Telemetry carriers: deterministic views of the given tables that stand in for sensor data.

burst: each event is one 3-second manoeuvre of 60 samples; native: events as
they are; lineitem: pure columns. Every formula is written for Spark here and for
DuckDB in the *_SQL texts, which the check queries start with.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SAMPLES = 60
WINDOW_S = 3


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def epoch(ts: Column) -> Column:
    """Whole seconds since 1970 of a timestamp without zone, read as UTC."""
    return F.unix_timestamp(ts.cast("timestamp"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, vehicle_id, ts, event_type, value, k, epoch_s."""
    e = table(spark, sf_dir, "events")
    return e.select("event_id", F.col("user_id").alias("vehicle_id"), "ts", "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("k"), epoch(F.col("ts")).alias("epoch_s"))


def wave(a: int, b: int, c: int) -> Column:
    """A repeatable value in [-1, 1] of an event and a sample number."""
    return (F.pmod(F.col("event_id") * a + F.col("i") * b + c, F.lit(101)) - 50) / 50.0


def burst(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vehicle_id, event_id, i, win_start, x, y, z, k, event_type, value: 60 samples an event."""
    e = events(spark, sf_dir).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(SAMPLES - 1))))
    k, v = F.col("k"), F.col("value")
    return e.select(
        "vehicle_id", "event_id", "i", (F.floor(F.col("epoch_s") / WINDOW_S) * WINDOW_S).alias("win_start"), "epoch_s",
        (wave(31, 17, 7) * v / 50.0).alias("x"), (wave(43, 29, 11) * k / 50.0 + 0.0).alias("y"), (wave(59, 37, 3) * (v + k) / 100.0 + 9.81).alias("z"),
        "k", "event_type", "value",
    )


def burst_axes(event_id, k, value):
    """x, y and z of the burst samples of events, one row an event, of numpy columns."""
    import numpy as np

    i = np.arange(SAMPLES)
    x, y, z = (((event_id[:, None] * a + i * b + c) % 101 - 50) / 50.0 for a, b, c in ((31, 17, 7), (43, 29, 11), (59, 37, 3)))
    return x * value[:, None] / 50.0, y * k[:, None] / 50.0, z * (value + k)[:, None] / 100.0 + 9.81


def burst_magnitudes(event_id, k, value):
    """The magnitudes of the burst samples of events, one row an event, of numpy columns."""
    import numpy as np

    x, y, z = burst_axes(event_id, k, value)
    return np.sqrt(x * x + y * y + z * z)


def native(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vehicle_id, event_id, epoch_s, x, y, z: one sample an event."""
    rank = F.create_map(*[F.lit(x) for p in zip(EVENT_TYPES, range(5), strict=True) for x in p])
    return events(spark, sf_dir).select("vehicle_id", "event_id", "epoch_s", F.col("value").alias("x"), F.col("k").cast("double").alias("y"), rank[F.col("event_type")].cast("double").alias("z"))


#: Fixed values of the given table.
EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]


def lineitem_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vehicle_id (supplier), quarter, epoch_s, x, y, z."""
    s = table(spark, sf_dir, "lineitem")
    return s.select(F.col("l_suppkey").alias("vehicle_id"), (F.year("l_shipdate") * 4 + F.quarter("l_shipdate") - 1).cast("long").alias("win_start"), epoch(F.col("l_shipdate")).alias("epoch_s"), F.col("l_quantity").alias("x"), (F.col("l_extendedprice") / 2000.0).alias("y"), (F.col("l_discount") * 100.0).alias("z"))


def landmarks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """landmark_id, name, zone, zone_id, lat, lon: a grid of 25 places in five zones. A directory, so its size is bounded."""
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    key = F.col("n_nationkey")
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select(key.cast("int").alias("landmark_id"), F.col("n_name").alias("name"), F.col("r_name").alias("zone"), F.col("r_regionkey").cast("int").alias("zone_id"), (F.pmod(key, F.lit(5)) * 0.004 + 40.10).alias("lat"), (F.floor(key / 5) * 0.005 - 88.23).alias("lon"))


def fix_columns() -> dict[str, Column]:
    """lat, lon and quality of an event with k and event_id."""
    place, e = F.pmod(F.col("k"), F.lit(25)), F.col("event_id")
    return {
        "lat": F.pmod(place, F.lit(5)) * 0.004 + 40.10 + (F.pmod(e * 7919, F.lit(3001)) - 1500) / 1e6,
        "lon": F.floor(place / 5) * 0.005 - 88.23 + (F.pmod(e * 104729, F.lit(3001)) - 1500) / 1e6,
        "quality": F.when(F.col("event_type") == "error", 0).otherwise(1),
    }


def fixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vehicle_id, event_id, epoch_s, lat, lon, quality, landmark."""
    own = events(spark, sf_dir)
    return own.select("vehicle_id", "event_id", "epoch_s", *[c.alias(n) for n, c in fix_columns().items()], F.pmod(F.col("k"), F.lit(25)).cast("int").alias("true_landmark"))


# ---- the same in DuckDB ----

EVENTS_SQL = """
ev AS (
  SELECT event_id, user_id AS vehicle_id, ts, event_type, value, CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT) AS k,
         CAST(floor(epoch(ts)) AS BIGINT) AS epoch_s FROM events
)"""

FIX_SQL = EVENTS_SQL + """, fx AS (
  SELECT vehicle_id, event_id, epoch_s, ((k % 25) % 5) * 0.004e0 + 40.10e0 + ((event_id * 7919) % 3001 - 1500) / 1e6 AS lat,
         ((k % 25) // 5) * 0.005e0 - 88.23e0 + ((event_id * 104729) % 3001 - 1500) / 1e6 AS lon,
         CASE WHEN event_type = 'error' THEN 0 ELSE 1 END AS quality, CAST(k % 25 AS INTEGER) AS true_landmark FROM ev
)"""

BURST_SQL = EVENTS_SQL + """, bu AS (
  SELECT vehicle_id, event_id, i, (epoch_s // 3) * 3 AS win_start, epoch_s, k, event_type, value,
         ((event_id * 31 + i * 17 + 7) % 101 - 50) / 50e0 * value / 50e0 AS x,
         ((event_id * 43 + i * 29 + 11) % 101 - 50) / 50e0 * k / 50e0 + 0e0 AS y,
         ((event_id * 59 + i * 37 + 3) % 101 - 50) / 50e0 * (value + k) / 100e0 + 9.81e0 AS z
  FROM ev, (SELECT unnest(range(60)) AS i) s
)"""

SUMMARY_SQL = BURST_SQL + """, su AS (
  SELECT vehicle_id, win_start, count(*) AS n, avg(sqrt(x*x + y*y + z*z)) AS mag_mean, var_pop(sqrt(x*x + y*y + z*z)) AS mag_var,
         quantile_cont(x, 0.01) AS x_p01, quantile_cont(x, 0.1) AS x_p10, quantile_cont(x, 0.9) AS x_p90, quantile_cont(x, 0.99) AS x_p99,
         quantile_cont(y, 0.01) AS y_p01, quantile_cont(y, 0.1) AS y_p10, quantile_cont(y, 0.9) AS y_p90, quantile_cont(y, 0.99) AS y_p99,
         quantile_cont(z, 0.01) AS z_p01, quantile_cont(z, 0.1) AS z_p10, quantile_cont(z, 0.9) AS z_p90, quantile_cont(z, 0.99) AS z_p99,
         max(event_id) AS event_id, arg_max(k, event_id) AS k, arg_max(event_type, event_id) AS event_type
  FROM bu GROUP BY vehicle_id, win_start
)"""

NATIVE_SQL = EVENTS_SQL + """, na AS (
  SELECT vehicle_id, event_id, epoch_s, value AS x, CAST(k AS DOUBLE) AS y,
         CAST(list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 AS DOUBLE) AS z FROM ev
)"""

LINEITEM_SQL = """
li AS (
  SELECT l_suppkey AS vehicle_id, CAST(year(l_shipdate) * 4 + quarter(l_shipdate) - 1 AS BIGINT) AS win_start,
         CAST(floor(epoch(l_shipdate)) AS BIGINT) AS epoch_s, l_quantity AS x, l_extendedprice / 2000e0 AS y, l_discount * 100e0 AS z FROM lineitem
)"""

LANDMARK_SQL = """
lm AS (
  SELECT CAST(n_nationkey AS INTEGER) AS landmark_id, n_name AS name, r_name AS zone, CAST(r_regionkey AS INTEGER) AS zone_id,
         (n_nationkey % 5) * 0.004e0 + 40.10e0 AS lat, (n_nationkey // 5) * 0.005e0 - 88.23e0 AS lon
  FROM nation JOIN region ON n_regionkey = r_regionkey
)"""

#: Metres between (a_lat, a_lon) and (b_lat, b_lon), as SQL.
HAVERSINE_SQL = "(2 * 6371000e0 * asin(sqrt(pow(sin(radians({b_lat} - {a_lat}) / 2), 2) + cos(radians({a_lat})) * cos(radians({b_lat})) * pow(sin(radians({b_lon} - {a_lon}) / 2), 2))))"


def haversine_sql(a: str, b: str) -> str:
    return HAVERSINE_SQL.format(a_lat=f"{a}.lat", a_lon=f"{a}.lon", b_lat=f"{b}.lat", b_lon=f"{b}.lon")
