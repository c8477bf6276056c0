"""Positions: distances, nearest landmarks, neighbourhoods, snapping, speed."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

EARTH_M = 6371000.0
CELL_DEGREES = 0.002
#: A landmark directory up to this size goes along as one array; a larger one is joined by cells.
ARRAY_LANDMARKS = 10_000


def haversine(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Metres between two positions."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.asin(F.sqrt(a)) * (2 * EARTH_M)


def nearest(df: DataFrame, landmarks: DataFrame, method: str = "auto") -> DataFrame:
    """df with landmark_id, landmark_m, place and zone of the closest landmark (ties: lowest id); null without a position.

    auto counts the directory: one broadcast array up to ARRAY_LANDMARKS places, cells beyond.
    """
    if method == "cells" or (method == "auto" and landmarks.count() > ARRAY_LANDMARKS):
        return nearest_by_cells(df, landmarks)
    spots = landmarks.agg(F.collect_list(F.struct("landmark_id", "lat", "lon", "name", "zone")).alias("_spots"))
    best = F.array_min(F.transform("_spots", lambda s: F.struct(haversine(F.col("lat"), F.col("lon"), s["lat"], s["lon"]).alias("d"), s["landmark_id"].alias("id"), s["name"].alias("name"), s["zone"].alias("zone"))))
    near = df.crossJoin(F.broadcast(spots)).withColumn("_best", F.when(F.col("lat").isNotNull() & F.col("lon").isNotNull(), best))
    return near.select(*df.columns, F.col("_best.id").alias("landmark_id"), F.col("_best.d").alias("landmark_m"), F.col("_best.name").alias("place"), F.col("_best.zone").alias("zone"))


def cell(v: Column, size: float = CELL_DEGREES) -> Column:
    return F.floor(v / size).cast("long")


def _around(v: Column, size: float) -> Column:
    return F.explode(F.array(*[cell(v, size) + d for d in (-1, 0, 1)]))


def nearest_by_cells(df: DataFrame, landmarks: DataFrame, size: float = 0.008) -> DataFrame:
    """As nearest, by equi-joins on grid cells.

    A row looks in the cells around its own. What it finds is proven nearest if it is no farther than a cell is wide;
    rows without such a find look again in cells four times as wide, up to the whole globe, where every place is a neighbour.
    """
    from ..plans.store import stored

    keyed = stored(df.withColumn("_id", F.monotonically_increasing_id()), "positions")
    left, done = keyed.where(F.col("lat").isNotNull() & F.col("lon").isNotNull()), keyed.where(F.col("lat").isNull() | F.col("lon").isNull()).select("_id", *[F.lit(None).cast(t).alias(c) for c, t in (("landmark_id", landmarks.schema["landmark_id"].dataType), ("landmark_m", "double"), ("place", "string"), ("zone", "string"))])
    if landmarks.isEmpty():
        return keyed.join(done.union(left.select("_id", *[F.lit(None)] * 4)), "_id").select(*df.columns, "landmark_id", "landmark_m", "place", "zone")
    while True:
        last = size >= 360
        spots = landmarks.select("landmark_id", F.col("lat").alias("_lat"), F.col("lon").alias("_lon"), F.col("name").alias("place"), "zone").withColumn("_cy", _around(F.col("_lat"), size)).withColumn("_cx", _around(F.col("_lon"), size))
        at = left.select("_id", "lat", "lon", cell(F.col("lat"), size).alias("_cy"), cell(F.col("lon"), size).alias("_cx"))
        both = at.join(spots, ["_cy", "_cx"], "left").withColumn("landmark_m", haversine(F.col("lat"), F.col("lon"), F.col("_lat"), F.col("_lon")))
        best = both.groupBy("_id", "lat", "lon").agg(F.min(F.when(F.col("landmark_m").isNotNull(), F.struct("landmark_m", "landmark_id", "place", "zone"))).alias("b"))
        # A cell's least width in metres, at the latitude where it is narrowest; near the date line nothing is proven.
        width = size * EARTH_M * math.pi / 180 * F.cos(F.radians(F.least(F.abs("lat") + size, F.lit(90.0)))) * 0.999
        proven = F.lit(last) | (F.col("b").isNotNull() & (F.col("b.landmark_m") <= width) & (F.abs("lon") + size <= 180))
        round_ = stored(best.select("_id", F.col("b.landmark_id").alias("landmark_id"), F.col("b.landmark_m").alias("landmark_m"), F.col("b.place").alias("place"), F.col("b.zone").alias("zone"), F.coalesce(proven, F.lit(False)).alias("_ok")), "nearest")
        done = done.union(round_.where("_ok").drop("_ok"))
        left = left.join(round_.where("not _ok").select("_id"), "_id", "left_semi")
        if last or round_.where("not _ok").isEmpty():
            return keyed.join(done, "_id").select(*df.columns, "landmark_id", "landmark_m", "place", "zone")
        size = min(360.0, size * 4)


def reach(radius_m: float, lat: float) -> tuple[float, float]:
    """Degrees of latitude and longitude that a radius around a latitude reaches, a little widened; 360 where it reaches a pole."""
    angle = radius_m / EARTH_M
    dlat = math.degrees(angle) * 1.001 + 1e-9
    if abs(lat) + dlat >= 90 or angle >= math.pi / 2:
        return dlat, 360.0
    return dlat, math.degrees(math.asin(min(1.0, math.sin(angle) / math.cos(math.radians(lat))))) * 1.001 + 1e-9


def within(df: DataFrame, lat: float, lon: float, radius_m: float) -> DataFrame:
    """Rows within a radius of one place; a bounding box that reaches the scan comes first. Across the date line the box has no sides."""
    dlat, dlon = reach(radius_m, lat)
    box = F.col("lat").between(lat - dlat, lat + dlat)
    if -180 <= lon - dlon and lon + dlon <= 180:
        box &= F.col("lon").between(lon - dlon, lon + dlon)
    return df.where(box).withColumn("distance_m", haversine(F.lit(lat), F.lit(lon), F.col("lat"), F.col("lon"))).where(F.col("distance_m") <= radius_m)


def _cells(a: DataFrame, b: DataFrame, radius_m: float, size: float) -> tuple[DataFrame, DataFrame]:
    """a with its cell (cy, cx), and b once in each cell around its own; cells are at least a radius wide.

    Cells lie in bands of latitude; each band has as many around the globe as are wide enough there, so neighbours
    are found at any latitude, for any radius and across the date line.
    """
    own = math.degrees(radius_m / EARTH_M) * 1.001 + 1e-9
    tall, wide = max(size, own), max(size, own * math.pi / 2)
    farthest = lambda cy: F.least(F.greatest(F.abs(cy), F.abs(cy + 1)) * tall + tall, F.lit(90.0))
    count = lambda cy: F.greatest(F.lit(1), F.floor(F.lit(360.0) * F.cos(F.radians(farthest(cy))) / wide).cast("long"))
    column = lambda lon, cy: F.pmod(F.floor((lon + 180) * count(cy) / 360.0).cast("long"), count(cy))
    left = a.withColumn("cy", cell(F.col("lat"), tall)).withColumn("cx", column(F.col("lon"), F.col("cy")))
    right = b.withColumn("cy", _around(F.col("lat"), tall))
    mine, n = column(F.col("lon"), F.col("cy")), count(F.col("cy"))
    return left, right.withColumn("cx", F.explode(F.array_distinct(F.array(*[F.pmod(mine + d, n) for d in (-1, 0, 1)]))))


def radius_join(a: DataFrame, b: DataFrame, radius_m: float, size: float = CELL_DEGREES) -> DataFrame:
    """Pairs (a_id, b_id, distance_m) within a radius, of frames with event_id, lat, lon: an equi-join on cells at least a radius wide."""
    left, right = _cells(a.select("event_id", "lat", "lon"), b.select("event_id", "lat", "lon"), radius_m, size)
    left, right = (x.select("cy", "cx", *[F.col(c).alias(f"{s}_{n}") for c, n in (("event_id", "id"), ("lat", "lat"), ("lon", "lon"))]) for x, s in ((left, "a"), (right, "b")))
    far = haversine(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon"))
    return left.join(right, ["cy", "cx"]).withColumn("distance_m", far).where((F.col("distance_m") <= radius_m) & (F.col("a_id") != F.col("b_id"))).select("a_id", "b_id", "distance_m")


#: Positions of a tile: a tile of two is taken as a whole where it lies inside or outside the radius.
TILE = 64


def _count_around(ax, ay, bx, by, weight, radius_m):
    """For each place of a (numpy latitudes and longitudes) the weight of the places of b within the radius.

    Both are cut into tiles. Bounds on the chord between two tiles' boxes decide most pairs of tiles as a whole;
    single places are compared by chord in the others, and by the haversine where that is too close to call.
    """
    import numpy as np

    def tiles(x, y):
        """Places in order of tile, unit vectors, and the tiles' bounds: strips of latitude, cut by longitude."""
        strips = max(1, round(math.sqrt(len(x) / TILE)))
        order = np.argsort(x, kind="stable")
        strip = np.empty(len(x), "int64")
        strip[order] = np.arange(len(x)) * strips // len(x)
        order = np.lexsort((y, strip))
        u, v = np.radians(x[order]), np.radians(y[order])
        at = np.stack([np.cos(u) * np.cos(v), np.cos(u) * np.sin(v), np.sin(u)])
        starts = np.arange(0, len(x), TILE)
        return order, at, starts, np.minimum.reduceat(at, starts, axis=1), np.maximum.reduceat(at, starts, axis=1)

    limit = (2 * math.sin(min(radius_m / EARTH_M, math.pi) / 2)) ** 2
    least, most = limit * (1 - 1e-6) - 1e-15, limit * (1 + 1e-6) + 1e-15
    ao, a, a_starts, a_lo, a_hi = tiles(ax, ay)
    bo, b, b_starts, b_lo, b_hi = tiles(bx, by)
    bw = weight[bo]
    tile_weight, total = np.add.reduceat(bw, b_starts), np.zeros(len(ax), "int64")
    for t, i in enumerate(a_starts):
        lo, hi, mine = a_lo[:, t, None], a_hi[:, t, None], slice(i, i + TILE)
        near = (np.maximum(0, np.maximum(b_lo - hi, lo - b_hi)) ** 2).sum(axis=0)
        far = (np.maximum(b_hi - lo, hi - b_lo) ** 2).sum(axis=0)
        inside = far <= least
        total[mine] += tile_weight[inside].sum()
        for j in b_starts[~inside & (near <= most)]:
            theirs = slice(j, j + TILE)
            chord = ((a[:, mine, None] - b[:, None, theirs]) ** 2).sum(axis=0)
            hit = chord <= limit
            p, q = np.nonzero((chord > least) & (chord < most))
            if len(p):
                la, oa, lb, ob = ax[ao[i + p]], ay[ao[i + p]], bx[bo[j + q]], by[bo[j + q]]
                s = np.sin(np.radians(lb - la) / 2) ** 2 + np.cos(np.radians(la)) * np.cos(np.radians(lb)) * np.sin(np.radians(ob - oa) / 2) ** 2
                hit[p, q] = np.arcsin(np.sqrt(np.minimum(s, 1.0))) * (2 * EARTH_M) <= radius_m
            total[mine] += hit @ bw[theirs]
    out = np.empty_like(total)
    out[ao] = total
    return out


def radius_counts(df: DataFrame, radius_m: float, size: float = CELL_DEGREES) -> DataFrame:
    """event_id and neighbours of the rows of df: how many pairs radius_join(df, df) has of it, without making them; no row where it has none.

    Rows of one place are counted first, and places are compared cell against the cells around it, tile by tile.
    """
    f = df.select("event_id", F.col("lat").cast("double").alias("lat"), F.col("lon").cast("double").alias("lon")).where("event_id is not null and lat is not null and lon is not null and not isnan(lat) and not isnan(lon)")
    places = f.groupBy("lat", "lon").agg(F.count(F.lit(1)).alias("n"))
    left, right = _cells(places, places, radius_m, size)

    def count(key, mine, others):
        import pyarrow as pa

        lat, lon = (mine.column(c).to_numpy() for c in ("lat", "lon"))
        if not len(lat) or not others.num_rows:
            return pa.table({"lat": lat[:0], "lon": lon[:0], "around": pa.array([], pa.int64())})
        around = _count_around(lat, lon, *(others.column(c).to_numpy() for c in ("lat", "lon", "n")), radius_m)
        return pa.table({"lat": lat, "lon": lon, "around": around})

    around = left.groupBy("cy", "cx").cogroup(right.groupBy("cy", "cx")).applyInArrow(count, "lat double, lon double, around long")
    # A row is no neighbour of rows with its own event_id, itself among them.
    own = F.aggregate(F.flatten(F.transform("at", lambda p: F.transform("at", lambda q: haversine(p["lat"], p["lon"], q["lat"], q["lon"])))), F.lit(0).cast("long"), lambda s, m: s + F.when(m <= radius_m, 1).otherwise(0))
    per = f.join(around, ["lat", "lon"]).groupBy("event_id").agg(F.sum("around").alias("around"), F.collect_list(F.struct("lat", "lon")).alias("at"))
    return per.select("event_id", (F.col("around") - F.when(F.size("at") == 1, 1).otherwise(own)).alias("neighbours")).where("neighbours > 0")


def speed(fixes: DataFrame) -> DataFrame:
    """fixes with metres a second since the vehicle's fix before; null for its first."""
    w = Window.partitionBy("vehicle_id").orderBy("epoch_s", "event_id")
    before = {c: F.lag(c).over(w) for c in ("lat", "lon", "epoch_s")}
    gap = F.col("epoch_s") - before["epoch_s"]
    return fixes.withColumn("speed", F.when(gap > 0, haversine(before["lat"], before["lon"], F.col("lat"), F.col("lon")) / gap))


def snap(df: DataFrame, landmarks: DataFrame) -> DataFrame:
    """Positions moved onto their nearest landmark, with the distance moved."""
    spots = landmarks.select("landmark_id", F.col("lat").alias("snapped_lat"), F.col("lon").alias("snapped_lon"))
    return nearest(df, landmarks).join(spots, "landmark_id", "left")
