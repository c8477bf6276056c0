"""Searches by distance at any latitude and distance, and questions with their slots, against brute force and SQL."""

import math
import random

import pytest
from pyspark.sql import functions as F

from telemetry_insight.functions import geo
from telemetry_insight.functions import questions as Q
from telemetry_insight.operators import answer_ops
from telemetry_insight.plans.store import LABELLED_SQL


def metres(a, b):
    (la, lo), (lb, lp) = a, b
    h = math.sin(math.radians(lb - la) / 2) ** 2 + math.cos(math.radians(la)) * math.cos(math.radians(lb)) * math.sin(math.radians(lp - lo) / 2) ** 2
    return 2 * geo.EARTH_M * math.asin(math.sqrt(h))


@pytest.fixture(scope="module")
def points():
    r = random.Random(9)
    out = [(lat + r.uniform(-0.01, 0.01), lon + r.uniform(-0.01, 0.01)) for lat, lon in ((0, 0), (40.1, -88.2), (60, 25), (-75, 100), (89.99, 10)) for _ in range(25)]
    return out + [(10 + r.uniform(-0.003, 0.003), (180 + r.uniform(-0.003, 0.003) + 180) % 360 - 180) for _ in range(20)]


@pytest.mark.parametrize("radius", [300.0, 900.0])
def test_radius_searches_equal_brute_force(spark, points, radius):
    d = spark.createDataFrame([(i, *p) for i, p in enumerate(points)], "event_id long, lat double, lon double")
    want = {(i, j) for i, p in enumerate(points) for j, q in enumerate(points) if i != j and metres(p, q) <= radius}
    got = [(x["a_id"], x["b_id"]) for x in geo.radius_join(d, d, radius).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    for i in (0, 30, 55, 80, 110, 130):
        assert {x["event_id"] for x in geo.within(d, *points[i], radius).collect()} == {i} | {b for a, b in want if a == i}


def test_nearest_by_cells_equals_the_array_at_any_distance(spark, points):
    rows = [(i, *p) for i, p in enumerate(points[::6])] + [(900, 40.2, -88.2), (901, -40.0, 170.0), (902, 10.0, 179.9999), (903, None, 1.0)]
    d = spark.createDataFrame(rows, "event_id long, lat double, lon double")
    spots = spark.createDataFrame([(1, 40.1, -88.2, "a", "z"), (2, 60.004, 25.02, "b", "z"), (3, 10.0, -179.99, "c", "z"), (4, 10.0, 179.9, "d", "z")], "landmark_id int, lat double, lon double, name string, zone string")
    key = lambda m: {x["event_id"]: (x["landmark_id"], None if x["landmark_m"] is None else round(x["landmark_m"], 6), x["place"], x["zone"]) for x in geo.nearest(d, spots, m).collect()}
    assert key("array") == key("cells") and key("cells")[902][0] == 3 and key("cells")[903] == (None,) * 4
    assert geo.nearest(d, spots.limit(0), "cells").where(F.col("landmark_id").isNotNull()).count() == 0


def test_slots_of_questions(spark):
    texts = ["How many VERY aggressive events?", "calm windows", "aggressively", "explain event #17, why?", "slightly unstable"]
    got = spark.createDataFrame([(t,) for t in texts], "text string").select(Q.label_of(F.col("text")), Q.event_of(F.col("text"))).collect()
    assert [tuple(x) for x in got] == [("Very Aggressive", None), ("Calm", None), (None, None), (None, 17), ("Slightly Unstable", None)]


def test_answers_count_what_was_asked(spark, data, twin):
    counts = dict(twin(f"WITH {LABELLED_SQL} SELECT label, count(*) FROM lw GROUP BY 1")[1])
    texts = ["Give the total number of calm windows", "How many moderate events were there?", "How many windows are there in total?", "Give the total number of very aggressive events"]
    answers = answer_ops.ask_batch(spark, data, texts)
    want = [counts["Calm"], counts["Moderate"], sum(counts.values()), counts.get("Very Aggressive", 0)]
    assert [int(Q.numbers_in(a.text)[-1]) for a in answers] == want and all(a.score == 100 for a in answers)
    every = answer_ops.ask_batch(spark, data, [t for _, t, _ in Q.QUESTIONS])
    assert [a.intent for a in every] == [i for _, _, i in Q.QUESTIONS]
