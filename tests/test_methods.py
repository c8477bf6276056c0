"""Worked numbers, invariants and edge cases of the methods."""

import pytest
from pyspark.sql import functions as F

from telemetry_insight.functions import analytics as A
from telemetry_insight.functions import edge, geo
from telemetry_insight.functions import profiles as P
from telemetry_insight.functions import questions as Q
from telemetry_insight.operators import baseline_ops, profile_ops
from telemetry_insight.plans.store import labelled_windows
from telemetry_insight.sources import carriers as C


def test_payload_numbers():
    assert edge.raw_bytes(20, 3) == 1584
    assert round(edge.saved_percent(1584, 420), 2) == 73.48
    assert round(2648 * 1584 / 2**20, 2) == 4.00 and round(2648 * 420 / 2**20, 2) == 1.06


def test_scores_and_gate():
    assert [Q.score(i) for i in range(7)] == [100, 80, 60, 40, 20, 0, 0]
    assert [Q.gate(s) for s in (100, 80, 60, 40)] == ["present", "present", "caution", "flag"]


def test_cost():
    assert round(Q.cost(235, 188) * 1e5, 2) == 2.68
    assert round(Q.cost(357, 148) * 1e5, 2) == 2.97


def test_published_profiles_are_named_in_order():
    got = P.named([(5.87, 17.98), (0.16, 10.97), (0.48, 13.56), (0.09, 10.32), (0.16, 11.65)])
    assert [c.label for c in got] == list(P.DRIVING)
    assert [c.center[1] for c in got] == [10.32, 10.97, 11.65, 13.56, 17.98]


def test_kmeans_objective_never_rises(spark, data):
    f = labelled_windows(spark, data).select(*P.FEATURES).cache()
    centers, last = P.seeds(f, 5), float("inf")
    for _ in range(4):
        j = f.agg(P.objective(f, centers).alias("j")).first()["j"]
        assert j <= last + 1e-9
        last, centers = j, P.lloyd_step(f, centers)


def test_empty_cluster_keeps_its_centre(spark):
    df = spark.createDataFrame([(0.0, 0.0), (1.0, 1.0)], "instability double, extreme double")
    assert P.lloyd_step(df, [(0.5, 0.5), (99.0, 99.0)])[1] == (99.0, 99.0)


def test_assignment_tie_takes_the_lower_cluster(spark):
    df = spark.createDataFrame([(1.0, 1.0)], "instability double, extreme double")
    assert P.assign(df, P.named([(0.0, 1.0), (2.0, 1.0)], P.MACHINE)).first()["cluster"] == 0


def test_silhouette_equals_the_library(spark, data):
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.feature import VectorAssembler

    w = labelled_windows(spark, data)
    v = VectorAssembler(inputCols=list(P.FEATURES), outputCol="features").transform(w.withColumn("prediction", F.col("rank").cast("int")))
    assert P.silhouette(w, cluster="rank").first()["silhouette"] == pytest.approx(ClusteringEvaluator().evaluate(v), abs=1e-9)


def test_null_and_nan_axes_are_dropped(spark):
    rows = [(1, 0, 1.0, 2.0, 2.0), (1, 0, None, 1.0, 1.0), (1, 0, float("nan"), 1.0, 1.0)]
    s = edge.summarize(spark.createDataFrame(rows, "vehicle_id long, win_start long, x double, y double, z double")).first()
    assert (s["n"], s["mag_mean"], s["mag_var"]) == (1, 3.0, 0.0)


def test_approximate_percentiles_are_close(spark, data):
    b = C.burst(spark, data)
    both = edge.summarize(b).select("vehicle_id", "win_start", F.col("x_p90").alias("e")).join(edge.summarize(b, method="approx").select("vehicle_id", "win_start", F.col("x_p90").alias("a")), ["vehicle_id", "win_start"])
    assert both.agg(F.avg(F.abs(F.col("e") - F.col("a"))).alias("d")).first()["d"] < 0.5


def test_packets_round_trip(spark, data):
    s = labelled_windows(spark, data)
    back = edge.decode_packet(edge.encode_packet(s))
    assert back.join(s.select("vehicle_id", "win_start", F.col("n").alias("m")), ["vehicle_id", "win_start"]).where("n = m").count() == s.count()


def test_nearest_by_cells_equals_array(spark, data):
    f, lm = C.fixes(spark, data), C.landmarks(spark, data)
    a = {r["event_id"]: r["landmark_id"] for r in geo.nearest(f, lm).collect()}
    assert a == {r["event_id"]: r["landmark_id"] for r in geo.nearest(f, lm, "cells").collect()}


def test_missing_fix_keeps_the_window(spark, data):
    df = spark.createDataFrame([(1, None, None), (2, 40.10, -88.23)], "event_id long, lat double, lon double")
    got = {r["event_id"]: r["landmark_id"] for r in geo.nearest(df, C.landmarks(spark, data)).collect()}
    assert got == {1: None, 2: 0}


def test_dwell_trace(spark):
    rows = [(1, i, t, p) for i, (t, p) in enumerate([(0, "a"), (3, "a"), (6, "a"), (100, "a"), (103, "b"), (106, "b")])]
    s = A.stays(spark.createDataFrame(rows, "vehicle_id long, event_id long, win_start long, zone string"), gap=60)
    assert sorted((r["place"], r["windows"], r["minutes"]) for r in s.collect()) == [("a", 1, 0.05), ("a", 3, 0.15), ("b", 2, 0.1)]


def test_intents(spark):
    got = Q.classify(Q.questions(spark), Q.lexicon(spark)).collect()
    assert all(r["intent"] == r["expected"] for r in got)


def test_checks_catch_their_own_corruption():
    facts = Q.Facts("t", {"count": 593}, [("NATION_1", 12)], "Calm")
    ok = {"numbers": 0, "places": 0, "tone": 0, "generic": 0}
    assert Q.issues("There were 593 events, 12 at NATION_1.", facts, ["NATION_1"]) == ok
    assert Q.issues("There were 27 events.", facts, ["NATION_1"]) == ok | {"numbers": 1}
    assert Q.issues("593 at NATION_99.", facts, ["NATION_1"]) == ok | {"places": 1}
    assert Q.issues("593, dangerous.", facts, ["NATION_1"]) == ok | {"tone": 1}
    assert Q.issues("I am sorry, 593.", facts, ["NATION_1"]) == ok | {"generic": 1}


def test_cache_calls_once_per_prompt_and_settings():
    cache, r = Q.Cache(), Q.TemplateResponder()
    for config in (Q.Config.macro(), Q.Config.macro(), Q.Config.micro()):
        cache.get_or_call("x", config, r.generate)
    assert (r.calls, cache.hits) == (2, 1)


def test_baseline_needs_six_calls_at_most(spark, data):
    chunks = baseline_ops.chunk(baseline_ops._rows(spark, data))
    assert baseline_ops.pick(chunks).count() <= 5
    log = baseline_ops.answer(spark, data, "How many?", Q.TemplateResponder())[1]
    assert log.count() == baseline_ops.pick(chunks).count() + 1


def test_registry_pins_versions(spark, tmp_path):
    path = f"file://{tmp_path}/registry"
    profile_ops.save_centroids(spark, path, P.VERSION_0)
    profile_ops.save_centroids(spark, path, P.named([(0.1, 10.0), (1.0, 12.0)], version=1))
    assert len(profile_ops.load_centroids(spark, path, 0)) == 5 and profile_ops.load_centroids(spark, path)[0].version == 1
    assert profile_ops.refresh_due(0, 10, 10) and profile_ops.refresh_due(0, 1, 10, drift=0.3) and not profile_ops.refresh_due(0, 1, 10)


def test_plans(spark, data):
    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    f = C.fixes(spark, data)
    assert "NestedLoop" not in plan(geo.radius_join(f, f, 100.0)) and "Cartesian" not in plan(geo.radius_join(f, f, 100.0))
    assert "Exchange hash" not in plan(P.assign(labelled_windows(spark, data), P.VERSION_0))
    assert "TakeOrderedAndProject" in plan(A.hotspots(labelled_windows(spark, data)))
