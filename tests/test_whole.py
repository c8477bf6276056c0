"""Queries that must cover all of their input, against brute force."""

import itertools
import math
import random
from collections import Counter, defaultdict

import numpy as np
from pyspark.sql import functions as F

from telemetry_insight.functions import distances, edge, geo
from telemetry_insight.functions import questions as Q
from telemetry_insight.operators import profile_ops, registry, workload_ops
from telemetry_insight.plans.store import labelled_windows, summaries
from telemetry_insight.sources import carriers as C


def run(spark, d, name):
    return registry.queries()[name](spark, d).collect()


def samples(spark, d):
    """Magnitudes by event and sample, from the carrier's axes."""
    return {(r["event_id"], r["i"]): math.sqrt(r["x"] ** 2 + r["y"] ** 2 + r["z"] ** 2) for r in C.burst(spark, d).select("event_id", "i", "x", "y", "z").collect()}


def test_every_sample_has_a_magnitude(spark, data):
    want = samples(spark, data)
    got = run(spark, data, "accel_magnitude")
    assert len(got) == len(want) == 60 * C.events(spark, data).count()
    assert all(abs(r["magnitude"] - want[r["event_id"], r["i"]]) < 1e-6 for r in got)


def test_every_event_has_vibration_features(spark, tmp_path):
    ids = [*range(5), 1999, 2000, 2001, 123456789]
    rows = [(e, 1, "2024-01-01 00:00:00", "view", 10.0 + e % 7, f'{{"k": {e % 90}}}') for e in ids]
    spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string, value double, props string").selectExpr("event_id", "user_id", "to_timestamp_ntz(ts) AS ts", "event_type", "value", "props").write.parquet(f"{tmp_path}/events.parquet")
    of = defaultdict(list)
    for (e, _), m in sorted(samples(spark, str(tmp_path)).items()):
        of[e].append(m)
    got = run(spark, str(tmp_path), "vibration_features")
    assert sorted(r["event_id"] for r in got) == ids
    for r in got:
        m = of[r["event_id"]]
        d = [x - sum(m) / len(m) for x in m]
        assert abs(r["rms"] - math.sqrt(sum(x * x for x in d) / len(d))) < 1e-5
        assert r["crossings"] == sum(a * b < 0 for a, b in zip(d, d[1:]))
        a, b = d[1:], d[:-1]
        ma, mb = sum(a) / len(a), sum(b) / len(b)
        corr = sum((x - ma) * (y - mb) for x, y in zip(a, b)) / math.sqrt(sum((x - ma) ** 2 for x in a) * sum((y - mb) ** 2 for y in b))
        assert abs(r["autocorrelation"] - corr) < 1e-5


def windows(spark, d):
    return {r["event_id"]: (r["instability"], r["extreme"], r["rank"]) for r in labelled_windows(spark, d).select("event_id", "instability", "extreme", "rank").collect()}


def near_pairs(w, eps):
    return {e: [o for o, (c, d, _) in w.items() if (a - c) * (a - c) + (b - d) * (b - d) <= eps * eps] for e, (a, b, _) in w.items()}


def test_density_covers_all_windows(spark, data):
    w = windows(spark, data)
    near = near_pairs(w, profile_ops._EPS)
    got = {r["event_id"]: (r["neighbours"], r["core"]) for r in run(spark, data, "density_core_points")}
    assert got == {e: (len(o), len(o) >= profile_ops._MIN) for e, o in near.items()}
    clusters, left = {}, {e for e, o in near.items() if len(o) >= profile_ops._MIN}
    while left:
        first = min(left)
        todo, n = [first], 0
        left.discard(first)
        while todo:
            n += 1
            new = [o for o in near[todo.pop()] if o in left]
            left.difference_update(new)
            todo += new
        clusters[first] = n
    assert {r["cluster"]: r["points"] for r in run(spark, data, "density_grid")} == clusters


def test_density_of_full_cells(spark):
    r = random.Random(3)
    w = {e: (r.choice([0.0, 0.07, 0.4]) + r.random() * 0.06, 10 + r.random() * 0.06, 0) for e in range(1500)}
    df = spark.createDataFrame([(e, *x) for e, x in w.items()], "event_id long, instability double, extreme double, rank int")
    assert {r["event_id"]: r["neighbours"] for r in profile_ops._cores(df).collect()} == {e: len(o) for e, o in near_pairs(w, profile_ops._EPS).items()}
    assert [(x["cluster"], x["points"]) for x in profile_ops._density_clusters(df).orderBy("cluster").collect()] == [(min(e for e in w if (w[e][0] > 0.3) == far), sum((w[e][0] > 0.3) == far for e in w)) for far in sorted((False, True), key=lambda far: min(e for e in w if (w[e][0] > 0.3) == far))]


def test_exact_silhouette_of_all_windows(spark, data, monkeypatch):
    monkeypatch.setattr(profile_ops, "_BLOCK", 300)
    w = windows(spark, data)
    size, total = Counter(r for *_, r in w.values()), 0.0
    for a, b, rank in w.values():
        far = defaultdict(float)
        for c, d, o in w.values():
            far[o] += math.hypot(a - c, b - d)
        if size[rank] > 1:
            own, other = far[rank] / (size[rank] - 1), min(far[o] / size[o] for o in size if o != rank)
            total += (other - own) / max(own, other)
    (got,) = run(spark, data, "silhouette_exact")
    assert got["points"] == len(w) and abs(got["silhouette"] - total / len(w)) < 2e-6


def mean_silhouette(rows):
    """Of (rank, a, b): mean over the rows that have one, by all pairs."""
    size, values = Counter(r for r, *_ in rows), []
    for rank, a, b in rows:
        far = defaultdict(float)
        for o, c, d in rows:
            far[o] += math.hypot(a - c, b - d)
        if size[rank] == 1:
            values.append(0.0)
        elif len(size) > 1:
            own, other = far[rank] / (size[rank] - 1), min(far[o] / size[o] for o in size if o != rank)
            values += [(other - own) / max(own, other)] if own or other else []
    return sum(values) / len(values) if values else None


def test_silhouette_of_dense_far_and_odd_places(spark, monkeypatch):
    monkeypatch.setattr(profile_ops, "_BLOCK", 40)
    g = np.random.default_rng(3)
    base = [(int(x > 0) + 2 * int(y > 1), float(x), float(y)) for x, y in g.normal(0, 1, (500, 2))]
    dense = [(2, 3 + float(x) * 1e-9, float(y) * 1e-9) for x, y in g.normal(0, 1, (150, 2))]
    twins = [(i % 2, 0.25, -0.5) for i in range(90)]
    cases = [base + dense + twins + [(4, -1e12, 3.0), (4, 1e13, 5.0), (9, 4.0, 4.0)], [(0, *x) for _, *x in base], twins, [(7, 1.0, 1.0)], [(i % 3, 0.0, 0.0) for i in range(9)], [(r, a * 1e-300, b * 1e-300) for r, a, b in base[:50]]]
    for rows in cases[:-1]:
        got = profile_ops.pairwise_silhouette(spark.createDataFrame(rows, "rank int, instability double, extreme double")).first()
        want = mean_silhouette(rows)
        assert got["points"] == len(rows) and (got["silhouette"] is None) == (want is None) and (want is None or abs(got["silhouette"] - want) < 2e-6)
    unknown = [(base + [(1, x, 1.0), (1, 2.0, 2.0)], math.nan) for x in (math.nan, math.inf, None)] + [([], None), (cases[-1], None)]
    for rows, want in unknown:
        got = profile_ops.pairwise_silhouette(spark.createDataFrame(rows, "rank int, instability double, extreme double")).first()
        assert got["points"] == len(rows) and (got["silhouette"] is None if want is None else math.isnan(got["silhouette"]))


def test_distances_by_cells_are_those_of_all_pairs_without_making_them():
    g = np.random.default_rng(5)
    a = np.concatenate([g.exponential(1, 8000), g.normal(3, 1e-6, 2000), [-1e6, 1e6]])
    b = np.concatenate([10 + a[:8000] + g.normal(0, 0.5, 8000), g.normal(-2, 1e-6, 2000), [5, -1e6]])
    rank, n = g.integers(0, 3, len(a)), g.integers(1, 4, len(a))

    def count(scale, kept, scale_kept):
        ok = np.isin(np.floor(a * scale_kept) + 1j * np.floor(b * scale_kept), kept[0] + 1j * kept[1]) if kept else np.ones(len(a), bool)
        cells, size = np.unique(np.floor(a[ok] * scale) + 1j * np.floor(b[ok] * scale), return_counts=True)
        return cells.real.astype(np.int64), cells.imag.astype(np.int64), size

    cells = distances.Cells((a.min(), b.min()), (a.max(), b.max()), 50, count)
    leaf = cells.leaf_of(a, b)
    assert (np.bincount(leaf, minlength=len(cells.leaves)) == cells.places).all() and cells.places.max() <= 50
    order = np.lexsort((rank, leaf))
    leaf, rank, a, b, n = (x[order] for x in (leaf, rank, a, b, n))
    charges = []
    for i, j in distances.runs(leaf * 3 + rank):
        x, y = cells.inside(leaf[i], a[i:j], b[i:j])
        charges.append((leaf[i], rank[i], (x * n[i:j, None]).T @ y))
    cells.charge(*(np.array(x) for x in zip(*charges, strict=True)))
    near, got = cells.near(), np.zeros((len(a), 3))
    assert sum(cells.places[i] * cells.places[p:q].sum() for i, runs in enumerate(near) for p, q in runs) < 0.05 * len(a) ** 2
    for at, total in distances.place_sums(leaf, rank, a, b, n, cells, near, range(len(near)), 3):
        got[at] = total
    some = g.permutation(len(a))[:500]
    want = np.sqrt((a[some, None] - a) ** 2 + (b[some, None] - b) ** 2) @ (np.eye(3)[rank] * n[:, None])
    assert (np.abs(got[some] - want) < 1e-11 * want).all()


def test_nodes_stand_for_the_places_of_cells_that_do_not_touch():
    t = np.linspace(-1, 1, 9)
    x, y = (np.repeat(t, 9), np.tile(t, 9))
    at = np.einsum("ni,nj->nij", distances.basis(x), distances.basis(y)).reshape(81, -1)
    for dx, dy in ((2, 0), (0, -2), (2, 1), (-2, 2), (3, 3)):
        far = np.hypot(x[:, None] - x - 2 * dx, y[:, None] - y - 2 * dy)
        assert (np.abs(at @ distances._kernel(dx, dy) @ at.T - far) < 1e-10 * far).all()


def test_windows_are_summarized_without_shuffling_samples(spark, tmp_path, data):
    x = lambda n: F.pmod(F.xxhash64("event_id"), F.lit(n))
    odd = C.table(spark, data, "events").withColumns({
        "value": F.when(x(11) == 0, None).when(x(11) == 1, math.nan).when(x(11) == 2, math.inf).otherwise(F.col("value")),
        "user_id": F.when(x(13) == 0, None).when(x(13) < 6, 1).otherwise(F.col("user_id")),
        "ts": F.when(x(13) < 3, None).when(x(13) < 6, F.date_trunc("day", "ts").cast("timestamp_ntz")).otherwise(F.col("ts")),
        "props": F.when(x(19) == 0, "{}").otherwise(F.col("props")),
    })
    odd.write.parquet(f"{tmp_path}/events.parquet")
    last = (F.max("event_id").alias("event_id"), F.max_by("k", "event_id").alias("k"), F.max_by("event_type", "event_id").alias("event_type"))
    for d in (data, str(tmp_path)):
        want = edge.summarize(C.burst(spark, d), extra=last).withColumns(C.fix_columns())
        got = summaries(spark, d)
        assert got.columns == want.columns and "Generate" not in got._jdf.queryExecution().executedPlan().toString()
        key = lambda r: (r["event_id"], str(r["win_start"]))
        a, b = (sorted(t.collect(), key=key) for t in (got, want))
        assert len(a) == len(b)
        for u, v in zip(a, b, strict=True):
            assert all(p == q or (math.isnan(p) and math.isnan(q)) or abs(p - q) <= 1e-12 * max(1, abs(q)) for p, q in zip(u, v, strict=True))


def test_radius_join_of_all_fixes(spark, data):
    f = [(math.radians(r["lat"]), math.radians(r["lon"])) for r in C.fixes(spark, data).collect()]
    near = lambda a, b: 2 * 6371000 * math.asin(math.sqrt(math.sin((a[0] - b[0]) / 2) ** 2 + math.cos(a[0]) * math.cos(b[0]) * math.sin((a[1] - b[1]) / 2) ** 2)) <= 100
    pairs = sum(near(a, b) for a, b in itertools.combinations(f, 2))
    assert [r["pairs"] for r in run(spark, data, "join_radius")] == [2 * pairs]


def test_sort_returns_the_null_keys_too(spark, data):
    rows = sorted(C.events(spark, data).collect(), key=lambda r: (r["k"] % 2, r["k"] if r["k"] % 2 == 0 else 0, -r["event_id"]))
    assert any(r["k"] % 2 for r in rows)
    assert sorted((r["position"], r["event_id"]) for r in run(spark, data, "sort_multi_null")) == [(n, r["event_id"]) for n, r in enumerate(rows, 1)]


def test_modes_are_compared_on_all_questions_and_runs(spark, data):
    got = run(spark, data, "workload_compare_modes")
    assert sorted(r["question"] for r in got) == sorted(workload_ops.MACRO)
    assert all(r["grounded_runs"] == r["raw_runs"] == 3 for r in got)
    assert all(r["grounded_tokens_spread"] == r["raw_tokens_spread"] == 0 and r["tokens_reduction"] == round(1 - r["grounded_tokens"] / r["raw_tokens"], 4) for r in got)


def test_ask_asks_every_question(spark, data):
    assert [(r["question"], r["intent"]) for r in run(spark, data, "ask")] == [(t, e) for _, t, e in Q.QUESTIONS]


def test_every_rare_row_gets_its_nearest(spark):
    r = random.Random(4)
    at = {e: (3 + r.random(), 14 + r.random()) for e in range(30)} | {100: (60.0, 14.0), 101: (3.9, 90.0), 102: (5.4, 15.4), 103: (61.7, 14.0)}
    rows = [(e, *x, "rare") for e, x in at.items()] + [(e, 1.0, 10.0 + e / 1000, "often") for e in range(200, 260)] + [(300, 7.0, 7.0, "alone")]
    df = spark.createDataFrame(rows, "event_id long, instability double, extreme double, label string")
    got = defaultdict(list)
    for x in profile_ops.oversample(df, "rare", 3).collect():
        got[x["event_id"]].append((x["instability"], x["extreme"]))
    assert sorted(got) == sorted(at)
    for e, (a, b) in at.items():
        c, d = min((x for o, x in at.items() if o != e), key=lambda x: (x[0] - a) ** 2 + (x[1] - b) ** 2)
        want = sorted((a + k * (c - a), b + k * (d - b)) for k in ((e * 7919 + j * 389) % 1000 / 1000 for j in range(2)))
        assert all(abs(x - y) < 1e-9 for p, q in zip(sorted(got[e]), want, strict=True) for x, y in zip(p, q))
    assert profile_ops.oversample(df, "alone").count() == profile_ops.oversample(df, "none").count() == 0


def test_rare_windows_are_doubled(spark, data):
    rare = sum(r["label"] == "Very Aggressive" for r in labelled_windows(spark, data).select("label").collect())
    assert len(run(spark, data, "minority_synthesis")) == rare


def own_events(spark, path, rows):
    """An events table of (event_id, vehicle, time or None, value, k) rows."""
    rows = [(e, v, t, "view", x, f'{{"k": {k}}}') for e, v, t, x, k in rows]
    spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string, value double, props string").selectExpr("event_id", "user_id", "to_timestamp_ntz(ts) AS ts", "event_type", "value", "props").write.parquet(f"{path}/events.parquet")
    return str(path)


def test_a_session_ends_with_a_gap_of_six_hours(spark, tmp_path):
    at = [(1, "00:00:00"), (1, "05:59:59"), (1, "11:59:59"), (2, "03:00:00.5"), (2, "09:00:00.25"), (3, None), (3, None), (3, "01:00:00")]
    d = own_events(spark, tmp_path, [(e, v, t and f"2024-01-01 {t}", 1.0, 1) for e, (v, t) in enumerate(at)])
    day = 1704067200
    want = [(1, day, 2), (1, day + 43199, 1), (2, day + 10800, 1), (2, day + 32400, 1), (3, day + 3600, 1), (3, None, 1), (3, None, 1)]
    assert sorted(((r["vehicle_id"], r["first_s"], r["samples"]) for r in run(spark, d, "dwell_sessions")), key=str) == sorted(want, key=str)


def test_vibration_features_are_worked_out_without_moving_samples(spark, tmp_path):
    """As over single samples, also for events without a value and two events of one id; the plan has no row a sample."""
    rows = [(2, 10.0, 5), (3, None, 5), (4, 10.0, 5), (4, 11.0, 7), (5, 120.0, 99), (-6, 3.5, 12), (None, 2.0, 3)]
    d = own_events(spark, tmp_path, [(e, 1, "2024-01-01 00:00:00", x, k) for e, x, k in rows])
    got = {r["event_id"]: r for r in run(spark, d, "vibration_features")}
    want = {r["event_id"]: r for r in edge.vibration(C.burst(spark, d), ["event_id"], ["i", "value"]).collect()}
    assert set(got) == set(want) == {-6, 2, 3, 4, 5, None}
    assert all(tuple(x[e])[1:] == (None, 0, None) for x in (got, want) for e in (3, None))
    for e in (-6, 2, 4, 5):
        assert abs(got[e]["rms"] - want[e]["rms"]) < 2e-6 and got[e]["crossings"] == want[e]["crossings"] and abs(got[e]["autocorrelation"] - want[e]["autocorrelation"]) < 2e-6
    rms, crossings, r, no_rms, no_r = edge.vibration_of(np.full((2, 4), 2.5), np.array([[True] * 4, [False] * 4]))
    assert (rms[0], crossings[0], no_rms.tolist(), no_r.tolist()) == (0.0, 0, [False, True], [False, True]) and math.isnan(r[0])
    plan = registry.queries()["vibration_features"](spark, d)._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan and "Window" not in plan


def test_neighbours_are_counted_without_pairs(spark, monkeypatch):
    """Many rows of few places, places at the radius, repeated ids, rows without a place; and no join on cells in the plan."""
    monkeypatch.setattr(geo, "TILE", 4)
    r = random.Random(5)
    spots = [(40.1 + r.random() * 0.004, -88.2 + r.random() * 0.004) for _ in range(150)] + [(60.0, 179.9999), (60.0, -179.9999), (89.9999, 10.0), (89.9999, -170.0)]
    spots += [(spots[0][0] + math.degrees(100 / geo.EARTH_M) + x, spots[0][1]) for x in (-1e-9, 1e-9)]
    rows = [(e, *spots[e % len(spots)]) for e in range(500)] + [(7, *spots[0]), (7, *spots[1]), (600, None, 1.0), (601, float("nan"), 1.0), (None, *spots[0])]
    df = spark.createDataFrame(rows, "event_id long, lat double, lon double")

    def far(a, b):
        (u, v), (x, y) = (tuple(map(math.radians, p[1:])) for p in (a, b))
        return 2 * geo.EARTH_M * math.asin(math.sqrt(math.sin((x - u) / 2) ** 2 + math.cos(u) * math.cos(x) * math.sin((y - v) / 2) ** 2))

    good = [x for x in rows if x[1] is not None and x[1] == x[1]]
    want = Counter(a[0] for a in good for b in good if None not in (a[0], b[0]) and a[0] != b[0] and far(a, b) <= 100)
    got = {x["event_id"]: x["neighbours"] for x in geo.radius_counts(df, 100.0).collect()}
    # A row without an id is nobody's neighbour in a join on different ids.
    assert got == dict(want)
    plan = registry.queries()["join_radius"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "[cy" not in plan.split("FlatMapCoGroupsInArrow")[0]


def test_block_distances_by_tiles(monkeypatch):
    """Two blocks, and a block with itself, whose ranks and tiles do not line up."""
    import pyarrow as pa

    monkeypatch.setattr(profile_ops, "_TILE", (3, 5))
    r = random.Random(6)
    x, y = ([{"event_id": e, "rank": r.choice([0, 1, 4]), "instability": r.random(), "extreme": 10 + r.random()} for e in ids] for ids in (range(23), range(100, 117)))
    kind = pa.list_(pa.struct([("event_id", pa.int64()), ("rank", pa.int32()), ("instability", pa.float64()), ("extreme", pa.float64())]))
    batch = pa.RecordBatch.from_arrays([pa.array([0, 0]), pa.array([1, 0]), pa.array([x, x], kind), pa.array([y, x], kind)], names=["x", "y", "x_rows", "y_rows"])
    got = defaultdict(float)
    for out in profile_ops._block_distances([batch]):
        for o in out.to_pylist():
            got[o["event_id"], o["rank"], o["o_rank"]] += o["far"]
    want = defaultdict(float)
    for a, b in [(a, b) for p, q in ((x, y), (y, x), (x, x)) for a in p for b in q]:
        want[a["event_id"], a["rank"], b["rank"]] += math.hypot(a["instability"] - b["instability"], a["extreme"] - b["extreme"])
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)
