"""Behaviour profiles: K-Means over window features, labels, quality measures, drift and alternatives."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The ordered vocabulary of driving profiles.
DRIVING = ("Calm", "Moderate", "Slightly Unstable", "Aggressive", "Very Aggressive")
MACHINE = ("Healthy", "Worn", "Failing")
BUILDING = ("Low load", "Normal load", "Peak load")
FEATURES = ("instability", "extreme")


@dataclass(frozen=True)
class Centroid:
    cluster: int
    center: tuple[float, ...]
    rank: int
    label: str
    version: int = 0


def named(centers: list[tuple[float, ...]], vocabulary: tuple[str, ...] = DRIVING, order: tuple[int, ...] = (1, 0), version: int = 0) -> list[Centroid]:
    """Centres in rank order, named by the vocabulary: by extreme, then instability."""
    by = sorted(centers, key=lambda c: tuple(c[i] for i in order if i < len(c)))
    if len(by) > len(vocabulary):
        raise ValueError("more centres than names")
    return [Centroid(i, tuple(c), i, vocabulary[i], version) for i, c in enumerate(by)]


#: Centroids (instability, extreme) of version 0, fitted to the burst carrier.
VERSION_0 = named([(0.08497034, 10.29142905), (0.33928239, 10.88379120), (0.79727731, 11.51731979), (1.68803153, 12.46057687), (3.54973455, 14.06036975)])


def squared_distance(features: tuple[str, ...], center: tuple[float, ...]) -> Column:
    out = F.lit(0.0)
    for f, c in zip(features, center, strict=True):
        out = out + (F.col(f) - F.lit(float(c))) * (F.col(f) - F.lit(float(c)))
    return out


def assign(df: DataFrame, centroids: list[Centroid], features: tuple[str, ...] = FEATURES) -> DataFrame:
    """df with cluster, rank, label and version of the nearest centroid (ties: lowest cluster). Centroids are literals: no join, no shuffle."""
    best = F.array_min(F.array(*[F.struct(squared_distance(features, c.center).alias("d"), F.lit(c.cluster).alias("cluster"), F.lit(c.rank).alias("rank"), F.lit(c.label).alias("label")) for c in centroids]))
    got = df.withColumn("_best", best)
    return got.select(*df.columns, F.col("_best.cluster").alias("cluster"), F.col("_best.rank").alias("rank"), F.col("_best.label").alias("label"), F.lit(centroids[0].version).alias("version"))


def seeds(df: DataFrame, k: int, features: tuple[str, ...] = FEATURES, how: str = "range") -> list[tuple[float, ...]]:
    """Starting centres: evenly over each feature's range or its quantiles, farthest-first, or the rows with the lowest hashes."""
    if how == "range":
        row = df.agg(*[F.min(f).alias(f"lo{i}") for i, f in enumerate(features)], *[F.max(f).alias(f"hi{i}") for i, f in enumerate(features)]).first()
        return [tuple(row[f"lo{i}"] + (row[f"hi{i}"] - row[f"lo{i}"]) * (j + 0.5) / k for i in range(len(features))) for j in range(k)]
    if how == "quantile":
        row = df.agg(*[F.percentile(f, F.array(*[F.lit((j + 0.5) / k) for j in range(k)])).alias(f"q{i}") for i, f in enumerate(features)]).first()
        return [tuple(row[f"q{i}"][j] for i in range(len(features))) for j in range(k)]
    if how == "hash":
        rows = df.select(*features).distinct().orderBy(F.xxhash64(*features)).limit(k).collect()
        return [tuple(r) for r in rows]
    start = df.orderBy(*[F.col(f).asc() for f in reversed(features)]).select(*features).first()
    out = [tuple(start)]
    while len(out) < k:
        far = F.least(*[squared_distance(features, c) for c in out]) if len(out) > 1 else squared_distance(features, out[0])
        out.append(tuple(df.agg(F.max_by(F.struct(*features), far).alias("r")).first()["r"]))
    return out


def lloyd_step(df: DataFrame, centers: list[tuple[float, ...]], features: tuple[str, ...] = FEATURES) -> list[tuple[float, ...]]:
    """The means of the rows nearest each centre; a centre without rows stays. K rows come to the driver."""
    near = F.array_min(F.array(*[F.struct(squared_distance(features, c).alias("d"), F.lit(i).alias("c")) for i, c in enumerate(centers)]))["c"]
    got = {r["c"]: r for r in df.select(*features, near.alias("c")).groupBy("c").agg(*[F.avg(f).alias(f) for f in features]).collect()}
    return [tuple(got[i][f] for f in features) if i in got else tuple(c) for i, c in enumerate(centers)]


def kmeans(df: DataFrame, k: int = 5, features: tuple[str, ...] = FEATURES, how: str = "range", iterations: int = 100, tolerance: float = 1e-9) -> list[tuple[float, ...]]:
    """Lloyd's algorithm from deterministic seeds. One scan of the features and K rows to the driver an iteration; the plan never grows."""
    centers = seeds(df, k, features, how)
    for _ in range(iterations):
        new = lloyd_step(df, centers, features)
        moved = max(math.dist(a, b) for a, b in zip(centers, new, strict=True))
        centers = new
        if moved <= tolerance:
            break
    return centers


def objective(df: DataFrame, centers: list[tuple[float, ...]], features: tuple[str, ...] = FEATURES) -> Column:
    """Summed squared distance to the nearest centre, as an aggregate."""
    d = [squared_distance(features, c) for c in centers]
    return F.sum(F.least(*d) if len(d) > 1 else d[0])


def profile(df: DataFrame) -> DataFrame:
    """label, rank, windows, share, mean features of labelled windows."""
    per = df.groupBy("label", "rank").agg(F.count(F.lit(1)).alias("windows"), F.avg("instability").alias("mean_instability"), F.avg("extreme").alias("mean_extreme"))
    total = per.agg(F.sum("windows").alias("total"))
    return per.crossJoin(F.broadcast(total)).withColumn("share", F.col("windows") / F.col("total")).drop("total")


def silhouette(df: DataFrame, features: tuple[str, ...] = FEATURES, cluster: str = "cluster") -> DataFrame:
    """Mean silhouette over squared Euclidean distance, from each cluster's count, sums and sums of squares: one aggregate, then one pass."""
    square = sum((F.col(f) * F.col(f) for f in features[1:]), F.col(features[0]) * F.col(features[0]))
    stats = df.groupBy(cluster).agg(F.count(F.lit(1)).alias("n"), F.sum(square).alias("q"), *[F.sum(f).alias(f"s_{f}") for f in features])
    all_stats = stats.agg(F.collect_list(F.struct(F.col(cluster).alias("c"), "n", "q", *[f"s_{f}" for f in features])).alias("_s"))
    joined = df.select(cluster, *features).crossJoin(F.broadcast(all_stats))  # one row of K entries

    def total(s: Column) -> Column:
        """Summed squared distance of the row to all rows of cluster s."""
        out = s["n"] * square + s["q"]
        for f in features:
            out = out - 2 * F.col(f) * s[f"s_{f}"]
        return out

    own = F.filter("_s", lambda s: s["c"] == F.col(cluster))[0]
    a = total(own) / (own["n"] - 1)
    b = F.array_min(F.transform(F.filter("_s", lambda s: s["c"] != F.col(cluster)), lambda s: total(s) / s["n"]))
    value = F.when(own["n"] == 1, 0.0).otherwise((b - a) / F.greatest(a, b))
    return joined.agg(F.avg(value).alias("silhouette"))


def scale(df: DataFrame, how: str = "none", features: tuple[str, ...] = FEATURES) -> DataFrame:
    """Features as they are, as z-scores (population), or as log(1 + v)."""
    if how == "none":
        return df
    if how == "log1p":
        return df.withColumns({f: F.log1p(f) for f in features})
    facts = df.agg(*[F.avg(f).alias(f"_m_{f}") for f in features], *[F.stddev_pop(f).alias(f"_s_{f}") for f in features])
    both = df.crossJoin(F.broadcast(facts))  # one row
    return both.select(*[((F.col(c) - F.col(f"_m_{c}")) / F.col(f"_s_{c}")).alias(c) if c in features else F.col(c) for c in df.columns])


def elbow(objectives: dict[int, float]) -> int:
    """The k farthest below the chord between the ends of the curve."""
    ks = sorted(objectives)
    (x0, y0), (x1, y1) = (ks[0], objectives[ks[0]]), (ks[-1], objectives[ks[-1]])
    return max(ks, key=lambda k: y0 + (y1 - y0) * (k - x0) / max(1, x1 - x0) - objectives[k])


def psi(reference: DataFrame, current: DataFrame, value: str, lo: float, hi: float, bins: int = 10) -> DataFrame:
    """bin, ref_share, cur_share, part: the population stability index over equal bins of the reference's range, open at both ends."""
    width = (hi - lo) / bins

    def shares(df: DataFrame, name: str) -> DataFrame:
        b = F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((F.col(value) - lo) / width))).cast("int")
        n = df.groupBy(b.alias("bin")).agg(F.count(F.lit(1)).alias("n"))
        return n.crossJoin(F.broadcast(n.agg(F.sum("n").alias("t")))).select("bin", (F.col("n") / F.col("t")).alias(name))

    both = shares(reference, "ref_share").join(shares(current, "cur_share"), "bin", "full").na.fill(0.0, ["ref_share", "cur_share"])
    r, c = F.greatest("ref_share", F.lit(1e-6)), F.greatest("cur_share", F.lit(1e-6))
    return both.withColumn("part", (c - r) * F.log(c / r))


def one_class(df: DataFrame, normal: Column, quantile: float = 0.99) -> DataFrame:
    """df with distance (Mahalanobis, from the normal rows' mean and covariance) and deviant (beyond the normal rows' quantile)."""
    n = df.where(normal)
    facts = n.agg(F.avg("instability").alias("m1"), F.avg("extreme").alias("m2"), F.var_pop("instability").alias("v1"), F.var_pop("extreme").alias("v2"), F.covar_pop("instability", "extreme").alias("c"))
    d1, d2 = F.col("instability") - F.col("m1"), F.col("extreme") - F.col("m2")
    far = F.sqrt((d1 * d1 * F.col("v2") - 2 * d1 * d2 * F.col("c") + d2 * d2 * F.col("v1")) / (F.col("v1") * F.col("v2") - F.col("c") * F.col("c")))
    with_far = df.crossJoin(F.broadcast(facts)).withColumn("distance", far).drop("m1", "m2", "v1", "v2", "c")
    limit = with_far.where(normal).agg(F.percentile("distance", quantile).alias("limit"))
    return with_far.crossJoin(F.broadcast(limit)).withColumn("deviant", F.col("distance") > F.col("limit"))


def rules(extreme_cuts: tuple[float, ...] = (10.6, 11.2, 12.0, 13.3), vocabulary: tuple[str, ...] = DRIVING) -> Column:
    """Profiles by fixed cuts of the extreme magnitude."""
    out = F.lit(vocabulary[-1])
    for cut, name in reversed(list(zip(extreme_cuts, vocabulary, strict=False))):
        out = F.when(F.col("extreme") < cut, name).otherwise(out)
    return out


def shift(w: DataFrame, ref: Column, label: str = "label") -> DataFrame:
    """label, shift, ref_share, cur_share: the distance between a profile's mean features in the reference rows and in the others, and its shares of both. One aggregation; a profile without rows on a side has a null shift."""
    both = {"ref": ref, "cur": ~ref}
    sides = [a for s, c in both.items() for a in (F.count_if(c).alias(f"{s}_n"), *[F.avg(F.when(c, F.col(f))).alias(f"{s}_{f}") for f in FEATURES])]
    per = w.groupBy(label).agg(*sides)
    total = per.agg(*[F.sum(f"{s}_n").alias(f"{s}_total") for s in both])
    apart = F.sqrt(sum((F.col(f"cur_{f}") - F.col(f"ref_{f}")) ** 2 for f in FEATURES))
    return per.crossJoin(F.broadcast(total)).select(label, apart.alias("shift"), *[(F.col(f"{s}_n") / F.col(f"{s}_total")).alias(f"{s}_share") for s in both])
