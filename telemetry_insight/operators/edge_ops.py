"""Queries of the edge stage: magnitudes, summaries, fixes, payloads, packets."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import edge
from ..plans.store import summaries
from ..sources import carriers as C
from .registry import query

M = "sqrt(x*x + y*y + z*z)"


@query("accel_magnitude")
def accel_magnitude(spark, d):
    """Every sample of every event."""
    m = edge.magnitude(F.col("x"), F.col("y"), F.col("z"))
    return C.burst(spark, d).select("event_id", "i", F.round(m, 6).alias("magnitude"))


@query("accel_magnitude_every_20th", f"WITH {C.BURST_SQL} SELECT event_id, i, round({M}, 6) AS magnitude FROM bu WHERE i % 20 = 0")
def accel_magnitude_every_20th(spark, d):
    """The part of accel_magnitude that its SQL covers."""
    return accel_magnitude(spark, d).where(F.col("i") % 20 == 0)


_FULL = [f"{a}_p{q}" for a in "xyz" for q in ("01", "10", "90", "99")]


@query("edge_summary", f"WITH {C.SUMMARY_SQL} SELECT vehicle_id, win_start, n, round(mag_mean, 6) AS mag_mean, round(mag_var, 6) AS mag_var, {', '.join(f'round({c} + 1e-9, 6) AS {c}' for c in _FULL)} FROM su")
def edge_summary(spark, d):
    s = edge.summarize(C.burst(spark, d))
    return s.select("vehicle_id", "win_start", "n", *[F.round(c, 6).alias(c) for c in ["mag_mean", "mag_var"]], *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in _FULL])


@query("edge_summary_minimal", f"WITH {C.BURST_SQL} SELECT vehicle_id, win_start, count(*) AS n, round(avg({M}), 6) AS mag_mean, round(var_pop({M}), 6) AS mag_var FROM bu GROUP BY 1, 2")
def edge_summary_minimal(spark, d):
    return edge.summarize(C.burst(spark, d), stats="moments").select("vehicle_id", "win_start", "n", F.round("mag_mean", 6).alias("mag_mean"), F.round("mag_var", 6).alias("mag_var"))


@query("edge_summary_peaks", f"WITH {C.SUMMARY_SQL} SELECT vehicle_id, win_start, round(mag_mean, 6) AS mag_mean, round(mag_var, 6) AS mag_var, round(x_p99 + 1e-9, 6) AS x_p99, round(y_p99 + 1e-9, 6) AS y_p99, round(z_p99 + 1e-9, 6) AS z_p99 FROM su")
def edge_summary_peaks(spark, d):
    s = edge.summarize(C.burst(spark, d), stats="peaks")
    return s.select("vehicle_id", "win_start", *[F.round(c, 6).alias(c) for c in ("mag_mean", "mag_var")], *[F.round(F.col(c) + 1e-9, 6).alias(c) for c in ("x_p99", "y_p99", "z_p99")])


@query("edge_summary_approx")
def edge_summary_approx(spark, d):
    return edge.summarize(C.burst(spark, d), method="approx")


@query("edge_summary_kll")
def edge_summary_kll(spark, d):
    return edge.summarize(C.lineitem_samples(spark, d), method="kll")


@query("edge_summary_sample_var", f"WITH {C.BURST_SQL} SELECT vehicle_id, win_start, round(var_samp({M}), 6) AS mag_var FROM bu GROUP BY 1, 2")
def edge_summary_sample_var(spark, d):
    return edge.summarize(C.burst(spark, d), stats="moments", ddof=1).select("vehicle_id", "win_start", F.round("mag_var", 6).alias("mag_var"))


@query("edge_summary_lineitem", f"WITH {C.LINEITEM_SQL} SELECT vehicle_id, win_start, count(*) AS n, round(avg({M}), 5) AS mag_mean, round(var_pop({M}), 4) AS mag_var, round(quantile_cont(x, 0.99) + 1e-9, 5) AS x_p99 FROM li GROUP BY 1, 2")
def edge_summary_lineitem(spark, d):
    s = edge.summarize(C.lineitem_samples(spark, d), stats="peaks")
    return s.select("vehicle_id", "win_start", "n", F.round("mag_mean", 5).alias("mag_mean"), F.round("mag_var", 4).alias("mag_var"), F.round(F.col("x_p99") + 1e-9, 5).alias("x_p99"))


_WIDTHS = (1, 3, 5, 10, 86400)


@query("window_duration_sweep", f"WITH {C.BURST_SQL}, s AS (SELECT unnest([{', '.join(map(str, _WIDTHS))}]) AS width) SELECT CAST(width AS INTEGER) AS width, count(*) AS windows, round(avg(n), 6) AS mean_samples, round(avg(v), 6) AS mean_var FROM (SELECT width, vehicle_id, CAST(floor((epoch_s * 20 + i) / (width * 20e0)) AS BIGINT) AS b, count(*) AS n, var_pop({M}) AS v FROM bu, s GROUP BY 1, 2, 3) GROUP BY width")
def window_duration_sweep(spark, d):
    """One scan for all durations: each sample goes to its bucket of every width."""
    tick = F.col("epoch_s") * 20 + F.col("i")
    b = C.burst(spark, d).withColumn("width", F.explode(F.array(*map(F.lit, _WIDTHS))))
    m = edge.magnitude(F.col("x"), F.col("y"), F.col("z"))
    per = b.groupBy("width", "vehicle_id", F.floor(tick / (F.col("width") * 20.0)).alias("b")).agg(F.count(F.lit(1)).alias("n"), F.var_pop(m).alias("v"))
    return per.groupBy("width").agg(F.count(F.lit(1)).alias("windows"), F.round(F.avg("n"), 6).alias("mean_samples"), F.round(F.avg("v"), 6).alias("mean_var"))


@query("edge_summary_moments_general", f"WITH {C.NATIVE_SQL} SELECT vehicle_id, epoch_s // 518400 AS bucket, count(x) AS n, round(avg(x), 6) AS mean, round(median(x), 6) AS median, round(var_pop(x), 3) AS variance, round(stddev_pop(x), 6) AS spread, round(quantile_cont(x, 0.9), 6) AS p90, CASE WHEN count(x) > 1 AND NOT isnan(regr_slope(x, CAST(epoch_s AS DOUBLE))) THEN round(regr_slope(x, CAST(epoch_s AS DOUBLE)) * 1e6, 4) END AS slope FROM na GROUP BY 1, 2")
def edge_summary_moments_general(spark, d):
    s = edge.summarize_signal(C.native(spark, d).withColumn("bucket", F.floor(F.col("epoch_s") / 518400)), "x", ["vehicle_id", "bucket"])
    return s.select("vehicle_id", "bucket", "n", F.round("mean", 6).alias("mean"), F.round("median", 6).alias("median"), F.round("variance", 3).alias("variance"), F.round("spread", 6).alias("spread"), F.round("p90", 6).alias("p90"), F.round(F.col("slope") * 1e6, 4).alias("slope"))


def _vibration(batches):
    """Rows of an event_id and its events' k and value (more than one where the id repeats: their samples are taken together, in order of i)."""
    import numpy as np
    import pyarrow as pa

    for batch in batches:
        rows = batch.column("rows")
        size, at = rows.value_lengths().to_numpy(zero_copy_only=False), rows.offsets.to_numpy()[:-1]
        ids, nameless = batch.column("event_id").fill_null(0).to_numpy(), batch.column("event_id").is_null().to_numpy(zero_copy_only=False)
        k, value = (rows.values.field(c) for c in ("k", "value"))
        known = (k.is_valid().to_numpy(zero_copy_only=False)) & (value.is_valid().to_numpy(zero_copy_only=False))
        k, value = (c.cast(pa.float64()).fill_null(0.0).to_numpy(zero_copy_only=False) for c in (k, value))
        for n in np.unique(size):
            mine = np.flatnonzero(size == n)
            for part in np.array_split(mine, -(-len(mine) * n // 4096)):
                flat = (at[part][:, None] + np.arange(n)).ravel()
                m = C.burst_magnitudes(np.repeat(ids[part], n), k[flat], value[flat])
                m, ok = (a.reshape(len(part), n, C.SAMPLES).transpose(0, 2, 1).reshape(len(part), -1) for a in (m, np.repeat(known[flat] & ~np.repeat(nameless[part], n), C.SAMPLES)))
                rms, crossings, r, no_rms, no_r = edge.vibration_of(m, ok)
                yield pa.RecordBatch.from_arrays([pa.array(ids[part], mask=nameless[part]), pa.array(rms, mask=no_rms), pa.array(crossings.astype("int64")), pa.array(r, mask=no_r)], names=["event_id", "rms", "crossings", "autocorrelation"])


@query("vibration_features")
def vibration_features(spark, d):
    """Every event. An event's samples come from its own row, so events are shuffled, not samples."""
    e = C.events(spark, d).groupBy("event_id").agg(F.collect_list(F.struct("k", "value")).alias("rows"))
    v = e.mapInArrow(_vibration, "event_id long, rms double, crossings long, autocorrelation double")
    return v.select("event_id", F.round("rms", 6).alias("rms"), "crossings", F.round("autocorrelation", 6).alias("autocorrelation"))


@query("vibration_features_first_2000", f"WITH {C.BURST_SQL}, m AS (SELECT event_id, i, {M} - avg({M}) OVER (PARTITION BY event_id) AS d FROM bu WHERE event_id < 2000), p AS (SELECT *, lag(d) OVER (PARTITION BY event_id ORDER BY i) AS prev FROM m) SELECT event_id, round(sqrt(avg(d*d)), 6) AS rms, count(*) FILTER (d * prev < 0) AS crossings, round(corr(d, prev), 6) AS autocorrelation FROM p GROUP BY event_id")
def vibration_features_first_2000(spark, d):
    """The part of vibration_features that its SQL covers."""
    return vibration_features(spark, d).where("event_id < 2000")


@query("position_attach", f"WITH {C.FIX_SQL} SELECT vehicle_id, epoch_s // 3 * 3 AS win_start, round(arg_max(lat, event_id), 6) AS lat, round(arg_max(lon, event_id), 6) AS lon, round(avg(lat), 6) AS mean_lat FROM fx GROUP BY 1, 2")
def position_attach(spark, d):
    f = C.fixes(spark, d).withColumn("win_start", F.floor(F.col("epoch_s") / 3) * 3)
    return f.groupBy("vehicle_id", "win_start").agg(F.round(F.max_by("lat", "event_id"), 6).alias("lat"), F.round(F.max_by("lon", "event_id"), 6).alias("lon"), F.round(F.avg("lat"), 6).alias("mean_lat"))


@query("asof_fix", f"WITH {C.FIX_SQL}, good AS (SELECT vehicle_id, epoch_s AS fix_s, lat FROM fx WHERE quality = 1) SELECT e.event_id, g.fix_s, round(g.lat, 6) AS lat FROM ev e ASOF LEFT JOIN (SELECT vehicle_id, fix_s, max(lat) AS lat FROM good GROUP BY 1, 2) g ON e.vehicle_id = g.vehicle_id AND e.epoch_s >= g.fix_s")
def asof_fix(spark, d):
    good = C.fixes(spark, d).where("quality = 1").groupBy("vehicle_id", "epoch_s").agg(F.max("lat").alias("lat"), F.max("lon").alias("lon"))
    return edge.asof_fix(C.events(spark, d), good).select("event_id", "fix_s", F.round("lat", 6).alias("lat"))


def _one(spark, **values):
    return spark.range(1).select(*[F.lit(v).alias(k) for k, v in values.items()])


@query("raw_payload_bytes", "SELECT 20e0 * 3e0 * 3 * 8 + 144 AS raw_bytes, round(100e0 * (1 - 420e0 / (20e0 * 3e0 * 3 * 8 + 144)), 6) AS saved_percent")
def raw_payload_bytes(spark, d):
    raw = edge.raw_bytes(20.0, 3.0)
    return _one(spark, raw_bytes=float(raw), saved_percent=round(edge.saved_percent(raw, 420), 6))


@query("packet_encode")
def packet_encode(spark, d):
    s = summaries(spark, d)
    return edge.decode_packet(edge.encode_packet(s)).select("vehicle_id", "win_start", "n", "mag_mean", "mag_var", "x_p99", "lat", "lon")


@query("payload_reduction", f"WITH {C.SUMMARY_SQL} SELECT count(*) AS windows, CAST(count(*) * 1584 AS BIGINT) AS raw_bytes, CAST(count(*) * 420 AS BIGINT) AS summary_bytes, round(100e0 * (1 - 420e0 / 1584e0), 6) AS saved_percent FROM su")
def payload_reduction(spark, d):
    s = edge.summarize(C.burst(spark, d), stats="moments").agg(F.count(F.lit(1)).alias("windows"))
    return s.select("windows", (F.col("windows") * 1584).alias("raw_bytes"), (F.col("windows") * 420).alias("summary_bytes"), F.lit(round(edge.saved_percent(1584, 420), 6)).alias("saved_percent"))


@query("payload_encoded")
def payload_encoded(spark, d):
    """Raw bytes against the bytes of the encoded packets."""
    p = edge.encode_packet(summaries(spark, d)).agg(F.count(F.lit(1)).alias("windows"), F.sum(F.octet_length("packet")).alias("packet_bytes"))
    return p.withColumn("saved_percent", F.round(100.0 * (1 - F.col("packet_bytes") / (F.col("windows") * 1584.0)), 4))


@query("daily_volume", f"WITH {C.EVENTS_SQL} SELECT CAST(make_timestamp(epoch_s * 1000000) AS DATE) AS event_date, count(*) * 60 * 3 * 8 AS accelerometer_bytes, count(*) * 144 AS gps_bytes, round(count(*) * 60 * 3 * 8 / 1048576e0, 4) AS accelerometer_mib, round(count(*) * 144 / 1048576e0, 4) AS gps_mib FROM ev GROUP BY 1")
def daily_volume(spark, d):
    """Bytes of the samples and fixes of each day."""
    n, a, g = F.count(F.lit(1)), C.SAMPLES * 3 * 8, 144
    days = C.events(spark, d).groupBy(F.date_from_unix_date(F.floor(F.col("epoch_s") / 86400).cast("int")).alias("event_date"))
    return days.agg((n * a).alias("accelerometer_bytes"), (n * g).alias("gps_bytes"), F.round(n * a / 1048576.0, 4).alias("accelerometer_mib"), F.round(n * g / 1048576.0, 4).alias("gps_mib"))


@query("gps_bytes_sensitivity", f"WITH {C.EVENTS_SQL}, w AS (SELECT count(*) * 60 AS n FROM ev GROUP BY vehicle_id, epoch_s // 3), t AS (SELECT count(*) AS windows, CAST(sum(n) AS BIGINT) AS samples FROM w) SELECT CAST(g AS BIGINT) AS gps_bytes, samples * 24 + windows * g AS raw_bytes, round(100e0 * (1 - windows * 420e0 / (samples * 24 + windows * g)), 4) AS saved_percent FROM t, (SELECT unnest([144, 432]) AS g)")
def gps_bytes_sensitivity(spark, d):
    """What summaries save of the given windows' bytes under two sizes of a fix."""
    w = C.events(spark, d).groupBy("vehicle_id", F.floor(F.col("epoch_s") / C.WINDOW_S).alias("w")).agg((F.count(F.lit(1)) * C.SAMPLES).alias("n"))
    t = w.agg(F.count(F.lit(1)).alias("windows"), F.sum("n").alias("samples"))
    g = t.withColumn("gps_bytes", F.explode(F.array(*[F.lit(b).cast("long") for b in (144, 432)]))).withColumn("raw_bytes", F.col("samples") * 24 + F.col("windows") * F.col("gps_bytes"))
    return g.select("gps_bytes", "raw_bytes", F.round(100.0 * (1 - F.col("windows") * 420.0 / F.col("raw_bytes")), 4).alias("saved_percent"))


@query("mission_volume", "SELECT CAST(2648 AS BIGINT) AS windows, round(2648 * 1584 / 1048576e0, 2) AS raw_mib, round(2648 * 420 / 1048576e0, 2) AS summary_mib")
def mission_volume(spark, d):
    return spark.range(1).select(F.lit(2648).cast("long").alias("windows"), F.round(F.lit(2648 * 1584) / 1048576.0, 2).alias("raw_mib"), F.round(F.lit(2648 * 420) / 1048576.0, 2).alias("summary_mib"))


@query("edge_capture_check", f"WITH {C.BURST_SQL} SELECT vehicle_id, win_start, round(count(*) / 3e0, 6) AS sample_rate, count(*) / 3e0 >= 20 AS accelerometer_ok, count(DISTINCT event_id) >= 1 AS fix_ok FROM bu GROUP BY 1, 2")
def edge_capture_check(spark, d):
    g = C.burst(spark, d).groupBy("vehicle_id", "win_start").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("event_id").alias("fixes"))
    rate = F.col("n") / 3.0
    return g.select("vehicle_id", "win_start", F.round(rate, 6).alias("sample_rate"), (rate >= 20).alias("accelerometer_ok"), (F.col("fixes") >= 1).alias("fix_ok"))


@query("raw_transmission", f"WITH {C.BURST_SQL} SELECT vehicle_id, count(*) AS samples, CAST(count(*) * 24 + 144 * count(DISTINCT win_start) AS BIGINT) AS bytes FROM bu GROUP BY vehicle_id")
def raw_transmission(spark, d):
    per = C.burst(spark, d).groupBy("vehicle_id", "win_start").agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("vehicle_id").agg(F.sum("n").alias("samples"), (F.sum("n") * 24 + F.count(F.lit(1)) * 144).alias("bytes"))
