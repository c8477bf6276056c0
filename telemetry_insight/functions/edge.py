"""Edge summaries: fixed windows of raw samples reduced to statistics; payload sizes; packets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
QUANTILES = (0.01, 0.1, 0.9, 0.99)


def magnitude(x: Column, y: Column, z: Column, gravity: float | None = None, how: str = "subtract") -> Column:
    """Length of an acceleration; gravity, if given, taken off it or divided out."""
    m = F.sqrt(x * x + y * y + z * z)
    if gravity is None:
        return m
    return m - gravity if how == "subtract" else m / gravity


def clean(samples: DataFrame) -> DataFrame:
    """Samples whose axes are all numbers: null and NaN readings go."""
    ok = F.lit(True)
    for a in AXES:
        ok = ok & F.col(a).isNotNull() & ~F.isnan(a)
    return samples.where(ok)


def summarize(samples: DataFrame, keys: tuple[str, ...] = ("vehicle_id", "win_start"), stats: str = "full", ddof: int = 0, method: str = "exact", quantiles: tuple[float, ...] = QUANTILES, extra: tuple[Column, ...] = ()) -> DataFrame:
    """One record per key: n, mean and variance of the magnitude, percentiles of the axes.

    stats: "moments" (mean and variance), "peaks" (also p99 of each axis), "full".
    method: "exact" (interpolated), "approx" (bounded memory), "kll" (mergeable sketches).
    """
    m = magnitude(*map(F.col, AXES))
    out = [F.count(F.lit(1)).alias("n"), F.avg(m).alias("mag_mean"), (F.var_samp(m) if ddof else F.var_pop(m)).alias("mag_var")]
    if stats != "moments":
        wanted = quantiles if stats == "full" else (0.99,)
        for a in AXES:
            if method == "exact":
                out.append(F.percentile(a, F.array(*[F.lit(q) for q in wanted])).alias(f"_{a}"))
            elif method == "approx":
                out.append(F.percentile_approx(a, list(wanted), 10000).alias(f"_{a}"))
            else:
                sketch = F.kll_sketch_agg_double(F.col(a).cast("double"))
                out.append(F.array(*[F.kll_sketch_get_quantile_double(sketch, F.lit(q)) for q in wanted]).alias(f"_{a}"))
    got = clean(samples).groupBy(*keys).agg(*out, *extra)
    if stats == "moments":
        return got
    named = [F.col(f"_{a}")[i].alias(f"{a}_p{round(q * 100):02d}") for a in AXES for i, q in enumerate(wanted)]
    keep = [c for c in got.columns if not (c.startswith("_") and c[1:] in AXES)]
    return got.select(*keep, *named)


def summary_of(axes, known):
    """summarize of numpy axes, one row a key and its samples in a row: n, mean and variance of the magnitude, and the percentiles of each axis. known marks the samples that count; a key without any has n 0."""
    import numpy as np

    n = known.sum(axis=1)
    with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
        m = np.sqrt(axes[0] * axes[0] + axes[1] * axes[1] + axes[2] * axes[2])
        mean = np.where(known, m, 0.0).sum(axis=1) / n
        d = np.where(known, m - mean[:, None], 0.0)
        out = [n, mean, (d * d).sum(axis=1) / n]
        rows, last = np.arange(len(n)), np.maximum(n - 1, 0)
        for a in axes:
            a = np.sort(np.where(known, a, np.nan), axis=1)  # those that do not count come last
            for q in QUANTILES:
                at = last * q
                lo, hi = np.floor(at).astype(int), np.ceil(at).astype(int)
                out.append(np.where(lo == hi, a[rows, lo], (hi - at) * a[rows, lo] + (at - lo) * a[rows, hi]))
    return out


def summarize_signal(samples: DataFrame, value: str, keys: list[str], time: str = "epoch_s") -> DataFrame:
    """Any one signal: centre, spread, percentiles and slope over time."""
    return samples.groupBy(*keys).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.median(value).alias("median"), F.var_pop(value).alias("variance"), F.stddev_pop(value).alias("spread"), F.percentile(value, 0.9).alias("p90"), F.regr_slope(F.col(value), F.col(time).cast("double")).alias("slope"))


def vibration(samples: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """Intensity (root mean square about the mean) and periodicity (zero crossings, correlation with the sample before) of the magnitude."""
    m = samples.withColumn("m", magnitude(*map(F.col, AXES)))
    whole = Window.partitionBy(*keys)
    w = whole.orderBy(*order)
    d = m.withColumn("d", F.col("m") - F.avg("m").over(whole)).withColumn("prev", F.lag("d").over(w))
    return d.groupBy(*keys).agg(F.sqrt(F.avg(F.col("d") * F.col("d"))).alias("rms"), F.sum(F.when(F.col("d") * F.col("prev") < 0, 1).otherwise(0)).alias("crossings"), F.corr("d", "prev").alias("autocorrelation"))


def vibration_of(m, known):
    """vibration of numpy magnitudes in order, one row a key: rms, crossings, autocorrelation (NaN for a constant), and where rms and autocorrelation are null. known marks the samples that are not null."""
    import numpy as np

    with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
        n = known.sum(axis=1)
        d = np.where(known, m - (np.where(known, m, 0.0).sum(axis=1) / n)[:, None], 0.0)
        both = known[:, 1:] & known[:, :-1]
        q, x, y = both.sum(axis=1), np.where(both, d[:, 1:], 0.0), np.where(both, d[:, :-1], 0.0)
        crossings = (x * y < 0).sum(axis=1)
        x, y = (np.where(both, a - (a.sum(axis=1) / q)[:, None], 0.0) for a in (x, y))
        return np.sqrt((d * d).sum(axis=1) / n), crossings, (x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1)), n == 0, q == 0


def extreme(two_sided: bool = False) -> Column:
    """Length of the axes' p99, or, two-sided, of the larger of |p1| and |p99| per axis."""
    parts = [F.greatest(F.abs(f"{a}_p01"), F.abs(f"{a}_p99")) if two_sided else F.col(f"{a}_p99") for a in AXES]
    return F.sqrt(sum((p * p for p in parts[1:]), parts[0] * parts[0]))


def raw_bytes(hz: float, seconds: float, axes: int = 3, reading: int = 8, gps: int = 144) -> float:
    """Bytes of a window sent as samples."""
    return hz * seconds * axes * reading + gps


def saved_percent(raw: float, summary: float) -> float:
    return 100.0 * (1 - summary / raw)


def asof_fix(samples: DataFrame, fixes: DataFrame, tolerance: int | None = None) -> DataFrame:
    """Each sample with the vehicle's latest fix at or before it (not older than tolerance seconds): one sort per vehicle, no join."""
    rows = samples.select("vehicle_id", "event_id", "epoch_s", F.lit(1).alias("kind"), F.lit(None).cast("double").alias("lat"), F.lit(None).cast("double").alias("lon"), F.lit(None).cast("long").alias("fix_s"))
    marks = fixes.select("vehicle_id", F.lit(None).cast("long").alias("event_id"), "epoch_s", F.lit(0).alias("kind"), "lat", "lon", F.col("epoch_s").alias("fix_s"))
    w = Window.partitionBy("vehicle_id").orderBy("epoch_s", "kind").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("fix_s").isNotNull(), F.struct("lat", "lon", "fix_s")), ignorenulls=True).over(w)
    got = rows.unionByName(marks).withColumn("fix", last).where("kind = 1")
    ok = F.lit(True) if tolerance is None else F.col("epoch_s") - F.col("fix.fix_s") <= tolerance
    return got.select("vehicle_id", "event_id", "epoch_s", F.when(ok, F.col("fix.lat")).alias("lat"), F.when(ok, F.col("fix.lon")).alias("lon"), F.when(ok, F.col("fix.fix_s")).alias("fix_s"))


PACKET = "v long, t long, n long, m double, s double, q array<double>, lat double, lon double"


def encode_packet(summary: DataFrame, digits: int = 4) -> DataFrame:
    """Summaries as compact JSON packets with one-letter keys."""
    q = F.array(*[F.round(f"{a}_p{round(p * 100):02d}", digits) for a in AXES for p in QUANTILES])
    body = F.struct(F.col("vehicle_id").alias("v"), F.col("win_start").alias("t"), "n", F.round("mag_mean", digits).alias("m"), F.round("mag_var", digits).alias("s"), q.alias("q"), F.round("lat", 6).alias("lat"), F.round("lon", 6).alias("lon"))
    return summary.select("vehicle_id", "win_start", F.to_json(body).alias("packet"))


def decode_packet(packets: DataFrame) -> DataFrame:
    """Packets back into summary columns; broken packets give nulls."""
    p = packets.withColumn("p", F.from_json("packet", PACKET))
    names = [f"{a}_p{round(q * 100):02d}" for a in AXES for q in QUANTILES]
    return p.select(F.col("p.v").alias("vehicle_id"), F.col("p.t").alias("win_start"), F.col("p.n").alias("n"), F.col("p.m").alias("mag_mean"), F.col("p.s").alias("mag_var"), *[F.get("p.q", F.lit(i)).alias(c) for i, c in enumerate(names)], F.col("p.lat").alias("lat"), F.col("p.lon").alias("lon"))
