"""Queries of the surrounding operators: scans, filters, joins, aggregates, windows, sets."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import analytics as A
from ..functions import geo
from ..plans.store import LABELLED_SQL, labelled_windows, shared_dir
from ..sources import carriers as C
from .baseline_ops import running_total
from .registry import query

L = f"WITH {LABELLED_SQL}"
E = f"WITH {C.EVENTS_SQL}"
SEV = "('Aggressive', 'Very Aggressive')"


def _n():
    return F.count(F.lit(1))


def _severe(w):
    return w.where(F.col("label").isin(*A.SEVERE))


@query("scan_parquet", "SELECT event_id, user_id FROM events")
def scan_parquet(spark, d):
    return C.table(spark, d, "events").select("event_id", "user_id")


@query("scan_json_packets")
def scan_json_packets(spark, d):
    """JSON with a broken row: the good ones typed, the broken one kept apart."""
    path = f"{shared_dir(spark)}/json-{uuid.uuid4().hex}"
    rows = C.events(spark, d).select(F.to_json(F.struct("event_id", "vehicle_id", "value")).alias("value"))
    rows.unionByName(spark.createDataFrame([("{broken",)], "value string")).write.text(path)
    j = spark.read.schema("event_id long, vehicle_id long, value double, _corrupt string").option("columnNameOfCorruptRecord", "_corrupt").json(path)
    return j.groupBy(F.col("_corrupt").isNotNull().alias("broken")).agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("value"), 2).alias("total"))


@query("scan_csv_export", f"{L} SELECT label, count(*) AS windows FROM lw GROUP BY 1")
def scan_csv_export(spark, d):
    path = f"{shared_dir(spark)}/csv-{uuid.uuid4().hex}"
    labelled_windows(spark, d).groupBy("label").agg(_n().alias("windows")).coalesce(1).write.csv(path, header=True)
    return spark.read.schema("label string, windows long").csv(path, header=True)


@query("sql_view_query", f"{L} SELECT place, count(*) AS events FROM lw WHERE quality = 1 AND label = 'Aggressive' GROUP BY 1 ORDER BY events DESC, place LIMIT 5")
def sql_view_query(spark, d):
    return spark.sql("SELECT place, count(*) AS events FROM {w} WHERE quality = 1 AND label = :label GROUP BY place ORDER BY events DESC, place LIMIT 5", {"label": "Aggressive"}, w=labelled_windows(spark, d))


@query("scan_variant_props", f"{E} SELECT k % 10 AS digit, count(*) AS events FROM ev GROUP BY 1")
def scan_variant_props(spark, d):
    v = C.table(spark, d, "events").select(F.variant_get(F.parse_json("props"), "$.k", "long").alias("k"))
    return v.groupBy((F.col("k") % 10).alias("digit")).agg(_n().alias("events"))


@query("replay_stream", "SELECT count(*) AS events FROM events")
def replay_stream(spark, d):
    from ..streaming import streams

    return streams.ingest(spark, d)


@query("sink_partitioned", f"{E} SELECT CAST(ts AS DATE) AS event_date, count(*) AS events FROM ev GROUP BY 1")
def sink_partitioned(spark, d):
    path = f"{shared_dir(spark)}/part-{uuid.uuid4().hex}"
    C.events(spark, d).withColumns({"event_date": F.col("ts").cast("date"), "bucket": F.pmod("vehicle_id", F.lit(4))}).repartition("event_date", "bucket").write.partitionBy("event_date", "bucket").parquet(path)
    return spark.read.parquet(path).groupBy("event_date").agg(_n().alias("events"))


@query("project_axes", f"WITH {C.NATIVE_SQL} SELECT event_id, round(x, 4) AS x, y, z FROM na")
def project_axes(spark, d):
    return C.native(spark, d).select("event_id", F.round("x", 4).alias("x"), "y", "z")


@query("filter_time_range", "SELECT event_id FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-12'")
def filter_time_range(spark, d):
    return C.table(spark, d, "events").where("ts >= timestamp_ntz'2024-01-10' and ts < timestamp_ntz'2024-01-12'").select("event_id")


@query("filter_fix", "SELECT event_type, count(*) AS events FROM events WHERE event_type <> 'error' GROUP BY 1")
def filter_fix(spark, d):
    return C.table(spark, d, "events").where("event_type <> 'error'").groupBy("event_type").agg(_n().alias("events"))


@query("filter_label_in", f"{L} SELECT event_id, label FROM lw WHERE label IN {SEV}")
def filter_label_in(spark, d):
    return _severe(labelled_windows(spark, d)).select("event_id", "label")


@query("filter_json_key", f"{E} SELECT count(*) AS events FROM ev WHERE k > 90")
def filter_json_key(spark, d):
    return C.events(spark, d).where("k > 90").agg(_n().alias("events"))


@query("filter_null_axis", f"{E} SELECT count(*) AS rows, count(*) FILTER (k % 10 = 0) AS null_rows, count(*) FILTER (k % 10 = 1) AS nan_rows, count(*) FILTER (k % 10 > 1) AS kept FROM ev")
def filter_null_axis(spark, d):
    """Axes made null or NaN by k: what the cleaning would drop, counted."""
    x = F.when(F.col("k") % 10 == 0, None).when(F.col("k") % 10 == 1, float("nan")).otherwise(F.col("value"))
    r = C.events(spark, d).select(x.alias("x"))
    return r.agg(_n().alias("rows"), F.count_if(F.col("x").isNull()).alias("null_rows"), F.count_if(F.col("x").isNotNull() & F.isnan("x")).alias("nan_rows"), F.count_if(F.col("x").isNotNull() & ~F.isnan("x")).alias("kept"))


@query("join_summary_landmark", f"{L} SELECT n_name AS nation, count(*) AS windows FROM lw JOIN nation ON landmark_id = n_nationkey GROUP BY 1")
def join_summary_landmark(spark, d):
    n = C.table(spark, d, "nation").select(F.col("n_nationkey").alias("landmark_id"), F.col("n_name").alias("nation"))
    return labelled_windows(spark, d).join(F.broadcast(n), "landmark_id").groupBy("nation").agg(_n().alias("windows"))


@query("join_samples_fixes", f"WITH {C.FIX_SQL} SELECT na.vehicle_id AS vehicle_id, count(*) AS samples FROM ev na JOIN fx ON na.event_id = fx.event_id AND fx.quality = 1 GROUP BY 1")
def join_samples_fixes(spark, d):
    f = C.fixes(spark, d).where("quality = 1").select("event_id").hint("merge")
    return C.native(spark, d).join(f, "event_id").groupBy("vehicle_id").agg(_n().alias("samples"))


@query("join_shuffle_hash", "SELECT o_orderpriority AS priority, count(*) AS lines, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_shuffle_hash(spark, d):
    o = C.table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_orderpriority").alias("priority")).hint("shuffle_hash")
    return C.table(spark, d, "lineitem").select("l_orderkey", "l_quantity").join(o, "l_orderkey").groupBy("priority").agg(_n().alias("lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("join_three_way", "SELECT r_name AS region, count(*) AS lines FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_three_way(spark, d):
    t = lambda n: C.table(spark, d, n)
    j = t("lineitem").select("l_suppkey").join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(t("nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy(F.col("r_name").alias("region")).agg(_n().alias("lines"))


@query("vehicles_with_severe", f"{L} SELECT DISTINCT vehicle_id FROM lw WHERE label = 'Very Aggressive'")
def vehicles_with_severe(spark, d):
    w = labelled_windows(spark, d)
    return w.select("vehicle_id").distinct().join(w.where("label = 'Very Aggressive'").select("vehicle_id"), "vehicle_id", "left_semi")


@query("vehicles_never_severe", f"{L} SELECT DISTINCT vehicle_id FROM lw WHERE vehicle_id NOT IN (SELECT vehicle_id FROM lw WHERE label = 'Very Aggressive')")
def vehicles_never_severe(spark, d):
    w = labelled_windows(spark, d)
    return w.select("vehicle_id").distinct().join(w.where("label = 'Very Aggressive'").select("vehicle_id"), "vehicle_id", "left_anti")


@query("drift_outer", f"{L}, a AS (SELECT label, count(*) AS n FROM lw WHERE event_date < DATE '2024-01-02' GROUP BY 1), b AS (SELECT label, count(*) AS m FROM lw WHERE event_date >= DATE '2024-01-29' GROUP BY 1) SELECT coalesce(a.label, b.label) AS label, coalesce(n, 0) AS before, coalesce(m, 0) AS after FROM a FULL JOIN b ON a.label = b.label")
def drift_outer(spark, d):
    w = labelled_windows(spark, d)
    a = w.where("event_date < date'2024-01-02'").groupBy("label").agg(_n().alias("before"))
    b = w.where("event_date >= date'2024-01-29'").groupBy("label").agg(_n().alias("after"))
    return a.join(b, "label", "full").na.fill(0)


@query("left_join_labels", "SELECT source, count(*) AS documents, count(l.doc_id) AS labelled FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def left_join_labels(spark, d):
    lab = C.table(spark, d, "labels").select("doc_id", F.lit(1).alias("one"))
    return C.table(spark, d, "documents").select("doc_id", "source").join(lab, "doc_id", "left").groupBy("source").agg(_n().alias("documents"), F.count("one").alias("labelled"))


@query("join_band_hours", f"{L}, bd AS (SELECT * FROM (VALUES ('night', 0, 5), ('morning', 6, 11), ('afternoon', 12, 16), ('evening', 17, 22)) t(band, lo, hi)) SELECT band, count(*) AS windows FROM lw JOIN bd ON hour BETWEEN lo AND hi GROUP BY 1")
def join_band_hours(spark, d):
    """A theta join against four rows."""
    b = spark.createDataFrame([("night", 0, 5), ("morning", 6, 11), ("afternoon", 12, 16), ("evening", 17, 22)], "band string, lo int, hi int")
    return labelled_windows(spark, d).join(F.broadcast(b), F.col("hour").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(_n().alias("windows"))


@query("join_radius")
def join_radius(spark, d):
    """All fixes with all fixes."""
    return geo.radius_counts(C.fixes(spark, d), 100.0).agg(F.coalesce(F.sum("neighbours"), F.lit(0)).cast("long").alias("pairs"))


@query("join_radius_first_200", f"WITH {C.FIX_SQL} SELECT count(*) AS pairs FROM fx a JOIN fx b ON a.event_id < 200 AND a.event_id <> b.event_id AND abs(a.lat - b.lat) < 0.001 AND {C.haversine_sql('a', 'b')} <= 100")
def join_radius_first_200(spark, d):
    """The same join for the fixes that its SQL covers."""
    f = C.fixes(spark, d)
    return geo.radius_join(f.where("event_id < 200"), f, 100.0).agg(_n().alias("pairs"))


@query("join_interval", f"{L} SELECT s.event_id AS severe_id, count(*) AS nearby FROM lw s JOIN lw o ON s.vehicle_id = o.vehicle_id AND s.label = 'Very Aggressive' AND o.event_id <> s.event_id AND abs(o.win_start - s.win_start) <= 43200 GROUP BY 1")
def join_interval(spark, d):
    """Windows of the same vehicle within twelve hours of a severe one: time buckets make it an equi-join."""
    w = labelled_windows(spark, d).select("vehicle_id", "event_id", "win_start", "label")
    s = w.where("label = 'Very Aggressive'").select("vehicle_id", F.col("event_id").alias("severe_id"), F.col("win_start").alias("at")).withColumn("b", F.explode(F.array(*[F.floor(F.col("at") / 43200) + i for i in (-1, 0, 1)])))
    o = w.withColumn("b", F.floor(F.col("win_start") / 43200))
    return s.join(o, ["vehicle_id", "b"]).where((F.col("event_id") != F.col("severe_id")) & (F.abs(F.col("win_start") - F.col("at")) <= 43200)).groupBy("severe_id").agg(_n().alias("nearby"))


@query("cross_small", f"{L}, g AS (SELECT n_name AS place, label FROM nation, (SELECT unnest(['Calm', 'Moderate', 'Slightly Unstable', 'Aggressive', 'Very Aggressive']) AS label)) SELECT g.place AS place, g.label AS label, count(lw.event_id) AS windows FROM g LEFT JOIN lw ON g.place = lw.place AND g.label = lw.label GROUP BY 1, 2")
def cross_small(spark, d):
    """Every landmark with every profile, zeros included: two tables of fixed size are crossed."""
    from ..functions.profiles import DRIVING

    grid = C.landmarks(spark, d).select(F.col("name").alias("place"), F.explode(F.array(*map(F.lit, DRIVING))).alias("label"))
    n = labelled_windows(spark, d).groupBy("place", "label").agg(_n().alias("windows"))
    return grid.join(n, ["place", "label"], "left").na.fill(0, ["windows"])


@query("agg_partial_final", "SELECT user_id AS vehicle_id, count(*) AS n, round(avg(value), 6) AS mean, min(value) AS least, max(value) AS most, round(stddev_samp(value), 6) AS spread FROM events GROUP BY 1")
def agg_partial_final(spark, d):
    return C.events(spark, d).groupBy("vehicle_id").agg(_n().alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.min("value").alias("least"), F.max("value").alias("most"), F.round(F.stddev("value"), 6).alias("spread"))


@query("agg_sorted_strings", f"{L} SELECT vehicle_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM lw GROUP BY 1")
def agg_sorted_strings(spark, d):
    return labelled_windows(spark, d).groupBy("vehicle_id").agg(F.array_join(F.array_sort(F.collect_set("label")), ",").alias("labels"))


@query("agg_distinct_vehicles", f"{L} SELECT place, count(DISTINCT vehicle_id) AS vehicles FROM lw GROUP BY 1")
def agg_distinct_vehicles(spark, d):
    return labelled_windows(spark, d).groupBy("place").agg(F.count_distinct("vehicle_id").alias("vehicles"))


@query("approx_vehicles")
def approx_vehicles(spark, d):
    """Distinct vehicles by sketches per date, merged into one per place."""
    per = labelled_windows(spark, d).groupBy("place", "event_date").agg(F.hll_sketch_agg("vehicle_id").alias("s"))
    return per.groupBy("place").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("vehicles"))


@query("agg_conditional", f"{L} SELECT route, count(*) AS windows, round(avg(CASE WHEN label IN {SEV} THEN 1e0 ELSE 0e0 END), 6) AS severe_share FROM lw GROUP BY 1")
def agg_conditional(spark, d):
    return labelled_windows(spark, d).groupBy("route").agg(_n().alias("windows"), F.round(F.avg(F.col("label").isin(*A.SEVERE).cast("double")), 6).alias("severe_share"))


@query("agg_grouping_sets", f"{L} SELECT label, zone, count(*) AS windows FROM lw GROUP BY GROUPING SETS ((label), (zone), (label, zone))")
def agg_grouping_sets(spark, d):
    return labelled_windows(spark, d).groupingSets([["label"], ["zone"], ["label", "zone"]], "label", "zone").agg(_n().alias("windows"))


@query("agg_rollup_zone_landmark", f"{L} SELECT zone, place, count(*) AS windows FROM lw GROUP BY ROLLUP (zone, place)")
def agg_rollup_zone_landmark(spark, d):
    return labelled_windows(spark, d).rollup("zone", "place").agg(_n().alias("windows"))


@query("agg_cube_label_band", f"{L} SELECT label, route, count(*) AS windows FROM lw GROUP BY CUBE (label, route)")
def agg_cube_label_band(spark, d):
    return labelled_windows(spark, d).cube("label", "route").agg(_n().alias("windows"))


@query("agg_pivot_band", f"{L} SELECT route, count(*) FILTER (hour BETWEEN 6 AND 11) AS morning, count(*) FILTER (hour BETWEEN 17 AND 22) AS evening FROM lw GROUP BY 1")
def agg_pivot_band(spark, d):
    return labelled_windows(spark, d).withColumn("band", A.band(F.col("hour"))).groupBy("route").pivot("band", ["morning", "evening"]).count().na.fill(0)


@query("agg_histogram", f"{L} SELECT CAST(floor(log10(instability) * 2) AS BIGINT) AS bin, count(*) AS windows FROM lw WHERE instability > 0 GROUP BY 1")
def agg_histogram(spark, d):
    return labelled_windows(spark, d).where("instability > 0").groupBy(F.floor(F.log10("instability") * 2).alias("bin")).agg(_n().alias("windows"))


@query("agg_median_mode", "SELECT user_id AS vehicle_id, round(median(value), 6) AS median FROM events GROUP BY 1")
def agg_median_mode(spark, d):
    return C.events(spark, d).groupBy("vehicle_id").agg(F.round(F.median("value"), 6).alias("median"))


@query("agg_having", f"{L} SELECT place, count(*) AS severe FROM lw WHERE label IN {SEV} GROUP BY 1 HAVING count(*) >= 3")
def agg_having(spark, d):
    return _severe(labelled_windows(spark, d)).groupBy("place").agg(_n().alias("severe")).where("severe >= 3")


@query("agg_corr_cov", f"{L} SELECT round(corr(instability, extreme), 6) AS correlation, round(covar_pop(instability, extreme), 6) AS covariance FROM lw")
def agg_corr_cov(spark, d):
    return labelled_windows(spark, d).agg(F.round(F.corr("instability", "extreme"), 6).alias("correlation"), F.round(F.covar_pop("instability", "extreme"), 6).alias("covariance"))




@query("rank_events_in_landmark", f"{L} SELECT event_id, row_number() OVER (PARTITION BY landmark_id ORDER BY k DESC, event_id) AS place_row, rank() OVER (PARTITION BY landmark_id ORDER BY k DESC) AS place_rank, dense_rank() OVER (PARTITION BY landmark_id ORDER BY k DESC) AS place_dense FROM lw")
def rank_events_in_landmark(spark, d):
    by = Window.partitionBy("landmark_id").orderBy(F.desc("k"))
    return labelled_windows(spark, d).select("event_id", F.row_number().over(Window.partitionBy("landmark_id").orderBy(F.desc("k"), "event_id")).cast("long").alias("place_row"), F.rank().over(by).cast("long").alias("place_rank"), F.dense_rank().over(by).cast("long").alias("place_dense"))


@query("ntile_instability", f"{L} SELECT event_id, ntile(5) OVER w AS quintile, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM lw WINDOW w AS (PARTITION BY route ORDER BY k, event_id)")
def ntile_instability(spark, d):
    w = Window.partitionBy("route").orderBy("k", "event_id")
    return labelled_windows(spark, d).select("event_id", F.ntile(5).over(w).cast("long").alias("quintile"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


_V = "PARTITION BY vehicle_id ORDER BY win_start, event_id"


def _vw():
    return Window.partitionBy("vehicle_id").orderBy("win_start", "event_id")


@query("lag_gap", f"{L} SELECT event_id, win_start - lag(win_start) OVER ({_V}) AS since, lead(win_start) OVER ({_V}) - win_start AS until FROM lw")
def lag_gap(spark, d):
    return labelled_windows(spark, d).select("event_id", (F.col("win_start") - F.lag("win_start").over(_vw())).alias("since"), (F.lead("win_start").over(_vw()) - F.col("win_start")).alias("until"))


@query("rolling_rows", f"{L} SELECT event_id, round(avg(extreme) OVER ({_V} ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean5 FROM lw")
def rolling_rows(spark, d):
    return labelled_windows(spark, d).select("event_id", F.round(F.avg("extreme").over(_vw().rowsBetween(-4, 0)), 6).alias("mean5"))


@query("rolling_time", f"{L} SELECT event_id, count(*) OVER (PARTITION BY vehicle_id ORDER BY win_start RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day_windows FROM lw")
def rolling_time(spark, d):
    return labelled_windows(spark, d).select("event_id", F.count(F.lit(1)).over(Window.partitionBy("vehicle_id").orderBy("win_start").rangeBetween(-86400, 0)).alias("day_windows"))


@query("cum_tokens", f"{E} SELECT event_id, CAST(sum(k) OVER (ORDER BY epoch_s, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS cum FROM ev")
def cum_tokens(spark, d):
    """A global running sum by range partitions and offsets."""
    from .baseline_ops import running_total

    return running_total(C.events(spark, d).select("event_id", "epoch_s", "k"), "k", ["epoch_s", "event_id"]).select("event_id", "cum")


@query("first_last_fix", f"WITH {C.FIX_SQL} SELECT vehicle_id, epoch_s // 86400 AS day, arg_min(true_landmark, event_id) AS first_place, arg_max(true_landmark, event_id) AS last_place FROM fx GROUP BY 1, 2")
def first_last_fix(spark, d):
    return C.fixes(spark, d).groupBy("vehicle_id", F.floor(F.col("epoch_s") / 86400).alias("day")).agg(F.min_by("true_landmark", "event_id").alias("first_place"), F.max_by("true_landmark", "event_id").alias("last_place"))


@query("topk_hotspots", f"{L} SELECT place, count(*) AS windows FROM lw WHERE label IN {SEV} GROUP BY 1 ORDER BY windows DESC, place LIMIT 10")
def topk_hotspots(spark, d):
    return _severe(labelled_windows(spark, d)).groupBy("place").agg(_n().alias("windows")).orderBy(F.desc("windows"), "place").limit(10)


@query("topk_per_zone", f"{L}, c AS (SELECT zone, place, count(*) AS windows FROM lw GROUP BY 1, 2) SELECT zone, place, windows FROM (SELECT *, row_number() OVER (PARTITION BY zone ORDER BY windows DESC, place) AS n FROM c) WHERE n <= 2")
def topk_per_zone(spark, d):
    c = labelled_windows(spark, d).groupBy("zone", "place").agg(_n().alias("windows"))
    return c.withColumn("n", F.row_number().over(Window.partitionBy("zone").orderBy(F.desc("windows"), "place"))).where("n <= 2").drop("n")


@query("sort_multi_null")
def sort_multi_null(spark, d):
    """event_id, position: the whole ordering, odd k as nulls last; range partitions and their sizes as offsets."""
    key = F.when(F.col("k") % 2 == 0, F.col("k"))
    one = C.events(spark, d).select("event_id", key.alias("key"), F.lit(1).alias("one"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return running_total(one, "one", [F.col("key").asc_nulls_last(), F.desc("event_id")], parts).select("event_id", F.col("cum").alias("position"))


@query("sort_multi_null_first_50", f"{E} SELECT event_id FROM ev ORDER BY CASE WHEN k % 2 = 0 THEN k END ASC NULLS LAST, event_id DESC LIMIT 50")
def sort_multi_null_first_50(spark, d):
    """The part of sort_multi_null that its SQL covers."""
    return sort_multi_null(spark, d).where("position <= 50").orderBy("position").select("event_id")


@query("limit_offset", "SELECT event_id FROM events ORDER BY value DESC, event_id LIMIT 20 OFFSET 40")
def limit_offset(spark, d):
    return C.table(spark, d, "events").orderBy(F.desc("value"), "event_id").offset(40).limit(20).select("event_id")


@query("union_sources", f"WITH {C.NATIVE_SQL},{C.LINEITEM_SQL} SELECT 'native' AS source, count(*) AS rows, count(event_id) AS with_event FROM na UNION ALL SELECT 'lineitem', count(*), 0 FROM li")
def union_sources(spark, d):
    u = C.native(spark, d).withColumn("source", F.lit("native")).unionByName(C.lineitem_samples(spark, d).withColumn("source", F.lit("lineitem")), allowMissingColumns=True)
    return u.groupBy("source").agg(_n().alias("rows"), F.count("event_id").alias("with_event"))


_HOT = "SELECT place FROM lw WHERE label IN ('Aggressive', 'Very Aggressive') AND event_date {}"


@query("intersect_hot", f"{L} {_HOT.format(chr(60) + ' DATE ' + repr('2024-01-15'))} INTERSECT {_HOT.format('>= DATE ' + repr('2024-01-15'))}")
def intersect_hot(spark, d):
    w = _severe(labelled_windows(spark, d))
    return w.where("event_date < date'2024-01-15'").select("place").intersect(w.where("event_date >= date'2024-01-15'").select("place"))


@query("except_hot", f"{L} {_HOT.format(chr(60) + ' DATE ' + repr('2024-01-15'))} EXCEPT {_HOT.format('>= DATE ' + repr('2024-01-15'))}")
def except_hot(spark, d):
    w = _severe(labelled_windows(spark, d))
    return w.where("event_date < date'2024-01-15'").select("place").subtract(w.where("event_date >= date'2024-01-15'").select("place"))


@query("scalar_subquery", f"{L} SELECT event_id FROM lw WHERE extreme > (SELECT quantile_cont(extreme, 0.99) FROM lw)")
def scalar_subquery(spark, d):
    return spark.sql("SELECT event_id FROM {w} WHERE extreme > (SELECT percentile(extreme, 0.99) FROM {w})", w=labelled_windows(spark, d))


@query("correlated_exists", f"{L} SELECT DISTINCT vehicle_id FROM lw a WHERE label = 'Calm' AND EXISTS (SELECT 1 FROM lw b WHERE b.vehicle_id = a.vehicle_id AND b.label = 'Very Aggressive' AND b.win_start > a.win_start)")
def correlated_exists(spark, d):
    return spark.sql("SELECT DISTINCT vehicle_id FROM {w} a WHERE label = 'Calm' AND EXISTS (SELECT 1 FROM {w} b WHERE b.vehicle_id = a.vehicle_id AND b.label = 'Very Aggressive' AND b.win_start > a.win_start)", w=labelled_windows(spark, d))


_REC = "seq AS (SELECT vehicle_id, landmark_id, row_number() OVER (PARTITION BY vehicle_id ORDER BY win_start, event_id) AS i FROM {w}), chain(vehicle_id, i, path) AS (SELECT vehicle_id, i, CAST(landmark_id AS {s}) FROM seq WHERE i = 1 UNION ALL SELECT s.vehicle_id, s.i, c.path || '>' || s.landmark_id FROM chain c JOIN seq s ON s.vehicle_id = c.vehicle_id AND s.i = c.i + 1 WHERE c.i < 5) SELECT vehicle_id, path FROM chain WHERE i = 5"


@query("recursive_stays", "WITH RECURSIVE " + LABELLED_SQL.strip() + ", " + _REC.format(w="lw", s="VARCHAR"))
def recursive_stays(spark, d):
    """The first five places of each vehicle, by a recursive query of bounded depth."""
    labelled_windows(spark, d).select("vehicle_id", "landmark_id", "win_start", "event_id").createOrReplaceTempView("_windows")
    return spark.sql("WITH RECURSIVE " + _REC.format(w="_windows", s="STRING"))


@query("unpivot_percentiles", f"WITH {C.SUMMARY_SQL} SELECT event_id, axis, round(v + 1e-9, 6) AS p99 FROM (UNPIVOT (SELECT event_id, x_p99, y_p99, z_p99 FROM su) ON x_p99, y_p99, z_p99 INTO NAME axis VALUE v)")
def unpivot_percentiles(spark, d):
    return labelled_windows(spark, d).unpivot("event_id", ["x_p99", "y_p99", "z_p99"], "axis", "v").select("event_id", "axis", F.round(F.col("v") + 1e-9, 6).alias("p99"))


@query("sample_rows", "SELECT event_id FROM events WHERE (event_id * 7919 + 42) % 10007 < 1000")
def sample_rows(spark, d):
    """A repeatable sample by hash, the feature of this operator."""
    return C.table(spark, d, "events").where("pmod(event_id * 7919 + 42, 10007) < 1000").select("event_id")


@query("label_quality_mix", "SELECT lang, quality, toxic, count(*) AS documents FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2, 3")
def label_quality_mix(spark, d):
    return C.table(spark, d, "documents").select("doc_id", "lang").join(C.table(spark, d, "labels"), "doc_id").groupBy("lang", "quality", "toxic").agg(_n().alias("documents"))


@query("document_numbers", "SELECT doc_id, CAST(len(regexp_extract_all(text, '[0-9]+([.][0-9]+)?')) AS INTEGER) AS numbers FROM documents WHERE text IS NOT NULL")
def document_numbers(spark, d):
    return C.table(spark, d, "documents").where("text is not null").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("[0-9]+([.][0-9]+)?"), F.lit(0))).alias("numbers"))


@query("page_text_chunks", "WITH t AS (SELECT page_id, CAST(ceil(length(regexp_replace(html, '<[^>]*>', '', 'g')) / 4e0) AS BIGINT) AS tokens FROM pages) SELECT page_id, tokens, CAST(floor((sum(tokens) OVER (ORDER BY page_id ROWS UNBOUNDED PRECEDING) - 1) / 3000e0) AS BIGINT) AS chunk_id FROM t")
def page_text_chunks(spark, d):
    from .baseline_ops import running_total

    t = C.table(spark, d, "pages").select("page_id", F.ceil(F.length(F.regexp_replace("html", "<[^>]*>", "")) / 4.0).cast("long").alias("tokens"))
    return running_total(t, "tokens", ["page_id"]).select("page_id", "tokens", F.floor((F.col("cum") - 1) / 3000.0).cast("long").alias("chunk_id"))


@query("benchmark_passages", "SELECT item_id, count(*) AS documents FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY 1")
def benchmark_passages(spark, d):
    """Documents that hold a test item word for word; the items are a small table of known size."""
    items = C.table(spark, d, "benchmark").select("item_id", F.col("text").alias("item"))
    one = items.agg(F.collect_list(F.struct("item_id", "item")).alias("items"))
    docs = C.table(spark, d, "documents").select("text").crossJoin(F.broadcast(one))
    return docs.select(F.explode(F.filter("items", lambda x: F.contains(F.col("text"), x["item"]))["item_id"]).alias("item_id")).groupBy("item_id").agg(_n().alias("documents"))


@query("order_gaps", "SELECT o_custkey AS customer, o_orderkey AS o_key, datediff('day', CAST(o_orderdate AS DATE), CAST(lead(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS DATE)) AS gap_days FROM orders")
def order_gaps(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return C.table(spark, d, "orders").select(F.col("o_custkey").alias("customer"), F.col("o_orderkey").alias("o_key"), F.datediff(F.lead("o_orderdate").over(w).cast("date"), F.col("o_orderdate").cast("date")).cast("long").alias("gap_days"))


@query("describe_quality", f"{L} SELECT 'events' AS stage, (SELECT count(*) FROM ev) AS rows UNION ALL SELECT 'windows', count(*) FROM lw UNION ALL SELECT 'good fixes', count(*) FILTER (quality = 1) FROM lw UNION ALL SELECT 'severe', count(*) FILTER (label IN {SEV}) FROM lw")
def describe_quality(spark, d):
    """Rows that each stage hands on."""
    w = labelled_windows(spark, d)
    s = w.agg(_n().alias("windows"), F.count_if(F.col("quality") == 1).alias("good fixes"), F.count_if(F.col("label").isin(*A.SEVERE)).alias("severe"))
    e = C.events(spark, d).agg(_n().alias("events"))
    return e.crossJoin(F.broadcast(s)).unpivot([], ["events", "windows", "good fixes", "severe"], "stage", "rows")
