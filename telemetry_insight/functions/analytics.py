"""Macro aggregations over labelled windows, one for each intent."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import geo

SEVERE = ("Aggressive", "Very Aggressive")


def hotspots(w: DataFrame, labels: tuple[str, ...] = ("Aggressive",), k: int = 3) -> DataFrame:
    """The k landmarks with most windows of these labels (good fixes only), mean instability, and the set's total and time span.

    Only one row per landmark is left before the ranking, so the totals cost nothing more.
    """
    per = w.where((F.col("quality") >= 1) & F.col("label").isin(*labels)).groupBy("landmark_id", "place").agg(F.count(F.lit(1)).alias("events"), F.avg("instability").alias("mean_instability"), F.min("win_start").alias("lo"), F.max("win_start").alias("hi"))
    total = per.agg(F.sum("events").alias("total_events"), F.min("lo").alias("first_window"), F.max("hi").alias("last_window"))
    top = per.orderBy(F.desc("events"), "landmark_id").limit(k).drop("lo", "hi")
    return top.crossJoin(F.broadcast(total))


def stays(w: DataFrame, gap: int, place: str = "zone", tau: float | None = None, width: int = 3) -> DataFrame:
    """vehicle_id, place, first, last, windows, minutes: runs of one vehicle's windows at one place, no gap beyond `gap` seconds."""
    low = w if tau is None else w.where(F.col("instability") <= tau)
    by = Window.partitionBy("vehicle_id").orderBy("win_start", "event_id")
    new = (F.lag(place).over(by) != F.col(place)) | (F.col("win_start") - F.lag("win_start").over(by) > gap)
    run = low.withColumn("_new", F.coalesce(new.cast("int"), F.lit(1))).withColumn("_run", F.sum("_new").over(by))
    g = run.groupBy("vehicle_id", "_run", F.col(place).alias("place")).agg(F.min("win_start").alias("first"), F.max("win_start").alias("last"), F.count(F.lit(1)).alias("windows"))
    return g.withColumn("minutes", (F.col("last") + width - F.col("first")) / 60.0).drop("_run")


def dwell(w: DataFrame, gap: int, place: str = "zone", tau: float | None = None) -> DataFrame:
    s = stays(w, gap, place, tau)
    return s.groupBy("place").agg(F.count(F.lit(1)).alias("stays"), F.sum("minutes").alias("minutes"), F.max("minutes").alias("longest"))


def band(hour: Column) -> Column:
    return F.when(hour.between(6, 11), "morning").when(hour.between(17, 22), "evening")


def compare_bands(w: DataFrame) -> DataFrame:
    """Per route: events, instability and speed in the morning and in the evening."""
    moving = geo.speed(w.where("quality = 1").withColumn("epoch_s", F.col("win_start")))
    b = moving.withColumn("band", band(F.col("hour"))).where("band is not null")
    p = b.groupBy("route").pivot("band", ["morning", "evening"]).agg(F.count(F.lit(1)).alias("events"), F.avg("instability").alias("instability"), F.avg("speed").alias("speed"))
    return p.withColumn("instability_change", F.col("evening_instability") - F.col("morning_instability"))


def around(w: DataFrame, lat: float, lon: float, radius_m: float = 250.0) -> DataFrame:
    near = geo.within(w.drop("distance_m"), lat, lon, radius_m)
    per = near.groupBy("label").agg(F.count(F.lit(1)).alias("windows"), F.avg("instability").alias("instability"), F.avg("extreme").alias("extreme"))
    return per.crossJoin(F.broadcast(per.agg(F.sum("windows").alias("t")))).withColumn("share", F.col("windows") / F.col("t")).drop("t")


def density(w: DataFrame, lat: float, lon: float, radius_m: float = 250.0) -> DataFrame:
    """Windows within radius_m of a point by hour, and per square kilometre of the circle."""
    near = geo.within(w.drop("distance_m"), lat, lon, radius_m)
    return near.groupBy("hour").agg(F.count(F.lit(1)).alias("windows")).withColumn("per_km2", F.col("windows") / (F.pi() * (radius_m / 1000) ** 2))


def idle_bands(w: DataFrame, gap: int, tau: float) -> DataFrame:
    """Per route: minutes of low-motion stays by the band they start in; idle_change is evening less morning."""
    s = stays(w, gap, "route", tau).withColumn("band", band(F.floor(F.col("first") % 86400 / 3600)))
    idle = lambda b: F.coalesce(F.sum(F.when(F.col("band") == b, F.col("minutes"))), F.lit(0.0)).alias(f"{b}_idle")
    return s.groupBy(F.col("place").alias("route")).agg(idle("morning"), idle("evening")).withColumn("idle_change", F.col("evening_idle") - F.col("morning_idle"))


def maneuver() -> Column:
    """What a window's widest axis says: braking, acceleration, turn or shock."""
    sx, sy, sz = (F.col(f"{a}_p99") - F.col(f"{a}_p01") for a in "xyz")
    return F.when((sx >= sy) & (sx >= sz), F.when(F.round(F.abs("x_p01"), 9) > F.round(F.abs("x_p99"), 9), "braking").otherwise("acceleration")).when(sy >= sz, "turn").otherwise("shock")
