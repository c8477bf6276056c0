"""Chunk sampling, clocked latency and answers of both modes."""

import numpy as np
import pytest

from telemetry_insight.functions import profiles as P
from telemetry_insight.operators import baseline_ops, registry, workload_ops


@pytest.mark.parametrize("ids", [[], [7], [3, 9, 4], [*range(0, 40, 3), 100, 1000], list(range(25))])
@pytest.mark.parametrize("m", [1, 5])
def test_pick_takes_one_of_each_run(spark, ids, m):
    chunks = spark.createDataFrame([(i,) for i in ids for _ in range(2)], "chunk_id long")
    runs = [r for r in np.array_split(sorted(ids), m) if len(r)]
    got = lambda mode: sorted(r["chunk_id"] for r in baseline_ops.pick(chunks, m, mode=mode).collect())
    assert got("systematic") == [r[0] for r in runs]
    assert got("stratified") == [min(r, key=lambda i: ((i * 7919 + 42) % 10007, i)) for r in runs]


def test_shift_of_profiles(spark):
    rows = [("a", 1.0, 1.0, True), ("a", 4.0, 5.0, False), ("b", 2.0, 2.0, True), ("b", 2.0, 2.0, True), ("c", 0.0, 0.0, False)]
    w = spark.createDataFrame(rows, "label string, instability double, extreme double, ref boolean")
    got = {r["label"]: (r["shift"], r["ref_share"], r["cur_share"]) for r in P.shift(w, w["ref"]).collect()}
    assert got == {"a": (5.0, 1 / 3, 0.5), "b": (None, 2 / 3, 0.0), "c": (None, 0.0, 0.5)}


def test_latency_names_the_simulated_stage(spark, data):
    rows = registry.queries()["latency"](spark, data).collect()
    assert len(rows) == 4 * len(workload_ops.MACRO)
    assert {r["stage"] for r in rows if r["simulated"]} == {"model"}
    assert all(r["seconds"] >= 0 for r in rows)


def test_grounded_answers_pass_the_checks(spark, data):
    rows = registry.queries()["workload_answer_quality"](spark, data).collect()
    assert len(rows) == 6 and {r["mode"] for r in rows} == {"grounded", "raw"}
    assert all(r["score"] == 100 and r["jargon"] == 0 and r["coordinates"] == 0 for r in rows if r["mode"] == "grounded")
