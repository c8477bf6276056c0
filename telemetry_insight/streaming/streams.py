"""Structured Streaming forms: summaries, sliding counts, sessions, duplicates, late rows, joins, state, restarts.

Sources are file streams over parts of the events table, written once to the shared
folder; every stream runs with availableNow from a checkpoint of its own.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import edge, profiles
from ..plans.store import shared_dir
from ..sources import carriers as C

_SCHEMA = "vehicle_id long, event_id long, epoch_s long, x double, y double, z double, at timestamp"


def _path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def feed(spark: SparkSession, d: str, parts: int = 4, again: bool = False) -> str:
    """The native carrier as `parts` files in time order; again: one part is sent twice."""
    path = _path(spark, "feed")
    rows = C.native(spark, d).withColumn("at", F.timestamp_seconds("epoch_s"))
    span = rows.agg(F.min("epoch_s").alias("lo"), F.max("epoch_s").alias("hi")).first()
    step = (span["hi"] - span["lo"]) // parts + 1
    for i in [*range(parts), *([1] if again else [])]:
        lo = span["lo"] + i * step
        rows.where(F.col("epoch_s").between(lo, lo + step - 1)).coalesce(1).write.mode("append").parquet(path)
    return path


def read(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(_SCHEMA).option("maxFilesPerTrigger", per_trigger).parquet(path)


def run(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None, out: str | None = None) -> DataFrame:
    """Write a stream's output as Parquet until its source is used up; the files read back."""
    spark = stream.sparkSession
    out = out or _path(spark, name)
    q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint or _path(spark, "checkpoint")).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(stream.schema).parquet(out)


def summarize(stream: DataFrame, window: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """Windowed summaries, given out once the watermark has passed a window's end."""
    m = edge.magnitude(F.col("x"), F.col("y"), F.col("z"))
    return stream.withWatermark("at", lateness).groupBy("vehicle_id", F.window("at", window)).agg(F.count(F.lit(1)).alias("n"), F.avg(m).alias("mag_mean"))


def summary(spark, d):
    s = summarize(read(spark, feed(spark, d), 10)).select("vehicle_id", F.unix_timestamp("window.start").alias("win_start"), "n", "mag_mean")
    return run(s, "summary").withColumn("mag_mean", F.round("mag_mean", 6))


def sliding(spark, d):
    """Severe samples an hour, every quarter of an hour."""
    s = read(spark, feed(spark, d), 10).where("x > 150").withWatermark("at", "1 hour").groupBy(F.window("at", "1 hour", "15 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return run(s.select(F.unix_timestamp("window.start").alias("win_start"), "n"), "sliding")


def sessions(spark, d):
    s = read(spark, feed(spark, d), 10).withWatermark("at", "1 hour").groupBy("vehicle_id", F.session_window("at", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return run(s.select("vehicle_id", F.unix_timestamp("session_window.start").alias("first_s"), "n"), "sessions")


def dedup(spark, d):
    s = read(spark, feed(spark, d, again=True), 10).withWatermark("at", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return run(s, "dedup").agg(F.count(F.lit(1)).alias("events"))


def late_rows(spark, d):
    """The first part of the feed sent again at the end: beyond the watermark, its rows are dropped and counted."""
    path = _path(spark, "feed")
    rows = C.native(spark, d).withColumn("at", F.timestamp_seconds("epoch_s"))
    cut = rows.agg(F.percentile("epoch_s", 0.5).cast("long").alias("c")).first()["c"]
    out, check = _path(spark, "late"), _path(spark, "checkpoint")
    dropped = 0
    for part in (rows.where(F.col("epoch_s") < cut), rows.where(F.col("epoch_s") >= cut), rows.where(F.col("epoch_s") < cut)):
        part.coalesce(1).write.mode("append").parquet(path)
        s = summarize(read(spark, path)).select("vehicle_id", "n")
        q = s.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start()
        q.awaitTermination()
        dropped += sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])
    total = spark.read.schema("vehicle_id long, n long").parquet(out).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("counted"))
    return total.withColumn("late_groups_dropped", F.lit(int(dropped)))


def static_assign(spark, d):
    """Live samples labelled with pinned centroids; centroids are literals, so there is no join."""
    s = read(spark, feed(spark, d), 10).withColumns({"extreme": F.sqrt(F.col("y") / 10 + 100), "instability": F.col("x") / 100})
    return run(profiles.assign(s, profiles.VERSION_0).select("event_id", "label", "version"), "assigned").groupBy("label").agg(F.count(F.lit(1)).alias("samples"))


def fix_join(spark, d):
    """Samples with fixes of the same vehicle within a second, both watermarked."""
    samples = read(spark, feed(spark, d), 10).withWatermark("at", "1 hour")
    path = _path(spark, "fixes")
    C.fixes(spark, d).where("quality = 1").select(F.col("vehicle_id").alias("fix_vehicle"), "lat", "lon", F.timestamp_seconds("epoch_s").alias("fix_at")).coalesce(1).write.parquet(path)
    fixes = spark.readStream.schema("fix_vehicle long, lat double, lon double, fix_at timestamp").parquet(path).withWatermark("fix_at", "1 hour")
    near = (F.col("vehicle_id") == F.col("fix_vehicle")) & (F.col("fix_at") >= F.col("at") - F.expr("interval 1 second")) & (F.col("fix_at") <= F.col("at") + F.expr("interval 1 second"))
    return run(samples.join(fixes, near).select("event_id", "lat", "lon"), "joined").agg(F.count(F.lit(1)).alias("pairs"))


def restart(spark, d):
    """The same query stopped and started again from its checkpoint as parts arrive: nothing lost, nothing twice."""
    path, check, out = _path(spark, "feed"), _path(spark, "checkpoint"), _path(spark, "restart")
    rows = C.native(spark, d).withColumn("at", F.timestamp_seconds("epoch_s"))
    for i in range(3):
        rows.where(F.col("event_id") % 3 == i).coalesce(1).write.mode("append").parquet(path)
        got = run(read(spark, path).select("event_id"), "restart", checkpoint=check, out=out)
    return got.agg(F.count(F.lit(1)).alias("events"), F.count_distinct("event_id").alias("distinct_events"))


def ingest(spark, d):
    """Buffered capture: a replayable source read a file at a time, every row once."""
    return run(read(spark, feed(spark, d)).select("event_id"), "ingest").agg(F.count(F.lit(1)).alias("events"))


def upsert(spark, d):
    """The latest event per vehicle, kept up to date by micro-batches that merge into versions of a table."""
    target = _path(spark, "latest")
    versions: list[str] = []

    def merge(batch: DataFrame, number: int) -> None:
        new = batch.groupBy("vehicle_id").agg(F.max("event_id").alias("event_id"))
        if versions:
            new = new.unionByName(spark.read.parquet(versions[-1])).groupBy("vehicle_id").agg(F.max("event_id").alias("event_id"))
        new.write.mode("overwrite").parquet(path := f"{target}/v{number}")
        versions.append(path)

    q = read(spark, feed(spark, d)).writeStream.foreachBatch(merge).option("checkpointLocation", _path(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(versions[-1])


def open_dwell(spark, d, limit_s: int = 6 * 3600, gap_s: int = 3600 * 24):
    """Alerts while a stay is still open: a vehicle whose samples keep within gap_s for longer than limit_s."""
    import pandas as pd

    def step(key, batches, state):
        first, last, told = state.get if state.exists else (None, None, False)
        alerts = []
        for pdf in batches:
            for s in sorted(pdf["epoch_s"].tolist()):
                if last is None or s - last > gap_s:
                    first, told = s, False
                last = s
                if not told and s - first >= limit_s:
                    alerts.append((key[0], first, s - first))
                    told = True
        state.update((first, last, told))
        yield pd.DataFrame(alerts, columns=["vehicle_id", "first_s", "open_s"])

    s = read(spark, feed(spark, d), 10).select("vehicle_id", "epoch_s").groupBy("vehicle_id").applyInPandasWithState(step, "vehicle_id long, first_s long, open_s long", "first long, last long, told boolean", "append", "NoTimeout")
    return run(s, "dwell")


def drift_monitor(spark, d, bins: int = 10, limit: float = 0.2):
    """Running shares of a feature per part of the feed against the first part's: the index of each batch, and a signal beyond the limit."""
    rows: list[tuple] = []
    reference: list[DataFrame] = []

    def watch(batch: DataFrame, number: int) -> None:
        held = batch.select("x")
        if not reference:
            path = _path(spark, "reference")
            held.write.parquet(path)
            reference.append(spark.read.parquet(path))
        got = profiles.psi(reference[0], held, "x", 0.0, 500.0, bins).agg(F.sum("part").alias("p")).first()["p"]
        rows.append((number, float(got), bool(got > limit)))

    q = read(spark, feed(spark, d)).writeStream.foreachBatch(watch).option("checkpointLocation", _path(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame(rows, "batch long, psi double, rebuild boolean")
