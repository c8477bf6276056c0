"""Queries of behaviour features and profiles: seeds, Lloyd steps, labels, measures, drift, alternatives, imbalance."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import functions as F

from ..functions import distances, edge, profiles as P
from ..plans.store import LABELLED_SQL, labelled_windows, shared_dir, stored, summaries
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"
F2 = "instability, extreme"


def _features(spark, d):
    return labelled_windows(spark, d).select("vehicle_id", "win_start", "event_id", "instability", "extreme", "event_date")


@query("extreme_magnitude", f"{L} SELECT event_id, round(extreme, 6) AS extreme, round(sqrt(pow(greatest(abs(x_p01), abs(x_p99)), 2) + pow(greatest(abs(y_p01), abs(y_p99)), 2) + pow(greatest(abs(z_p01), abs(z_p99)), 2)), 6) AS two_sided FROM lw")
def extreme_magnitude(spark, d):
    return summaries(spark, d).select("event_id", F.round(edge.extreme(), 6).alias("extreme"), F.round(edge.extreme(two_sided=True), 6).alias("two_sided"))


@query("instability", f"{L} SELECT event_id, round(instability, 6) AS instability FROM lw")
def instability(spark, d):
    return summaries(spark, d).select("event_id", F.round("mag_var", 6).alias("instability"))


@query("feature_scaling", f"{L}, m AS (SELECT avg(extreme) AS a, stddev_pop(extreme) AS s FROM lw) SELECT event_id, round((extreme - a) / s, 5) AS z_extreme, round(ln(1 + instability), 6) AS log_instability FROM lw, m")
def feature_scaling(spark, d):
    f = _features(spark, d)
    z = P.scale(f.select("event_id", "extreme", F.col("instability").alias("raw"), "instability"), "zscore")
    return z.select("event_id", F.round("extreme", 5).alias("z_extreme"), F.round(F.log1p("raw"), 6).alias("log_instability"))


def _seed_sql(body: str) -> str:
    return f"{L} {body}"


def _rows(spark, centers):
    return spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(centers)], "seed int, instability double, extreme double").select("seed", F.round("instability", 6).alias("instability"), F.round("extreme", 6).alias("extreme"))


@query("kmeans_seeds", _seed_sql("SELECT CAST(j AS INTEGER) AS seed, round(min(instability) + (max(instability) - min(instability)) * (j + 0.5e0) / 5, 6) AS instability, round(min(extreme) + (max(extreme) - min(extreme)) * (j + 0.5e0) / 5, 6) AS extreme FROM lw, (SELECT unnest(range(5)) AS j) GROUP BY j"))
def kmeans_seeds(spark, d):
    return _rows(spark, P.seeds(_features(spark, d), 5))


@query("kmeans_seeds_quantile", _seed_sql("SELECT CAST(j AS INTEGER) AS seed, round(quantile_cont(instability, [0.1, 0.3, 0.5, 0.7, 0.9])[j + 1], 6) AS instability, round(quantile_cont(extreme, [0.1, 0.3, 0.5, 0.7, 0.9])[j + 1], 6) AS extreme FROM lw, (SELECT unnest(range(5)) AS j) GROUP BY j"))
def kmeans_seeds_quantile(spark, d):
    return _rows(spark, P.seeds(_features(spark, d), 5, how="quantile"))


_FAR = "WITH RECURSIVE " + LABELLED_SQL.strip() + """, p AS (SELECT instability AS a, extreme AS b FROM lw),
c0 AS (SELECT a, b FROM p ORDER BY b, a LIMIT 1),
c1 AS (SELECT p.a, p.b FROM p, c0 ORDER BY pow(p.a - c0.a, 2) + pow(p.b - c0.b, 2) DESC LIMIT 1),
c2 AS (SELECT p.a, p.b FROM p, c0, c1 ORDER BY least(pow(p.a - c0.a, 2) + pow(p.b - c0.b, 2), pow(p.a - c1.a, 2) + pow(p.b - c1.b, 2)) DESC LIMIT 1)
SELECT 0 AS seed, round(a, 6) AS instability, round(b, 6) AS extreme FROM c0 UNION ALL SELECT 1, round(a, 6), round(b, 6) FROM c1 UNION ALL SELECT 2, round(a, 6), round(b, 6) FROM c2"""


@query("kmeans_seeds_farthest", _FAR)
def kmeans_seeds_farthest(spark, d):
    return _rows(spark, P.seeds(_features(spark, d), 3, how="farthest"))


@query("kmeans_seeds_hash")
def kmeans_seeds_hash(spark, d):
    return _rows(spark, P.seeds(_features(spark, d), 5, how="hash"))


def _lloyd_sql(steps: int, k: int = 5) -> str:
    qs = ", ".join(str((j + 0.5) / k) for j in range(k))
    out = f"{L}, p AS (SELECT instability AS a, extreme AS b FROM lw), k0 AS (SELECT j AS c, quantile_cont(a, [{qs}])[j + 1] AS ca, quantile_cont(b, [{qs}])[j + 1] AS cb FROM p, (SELECT unnest(range({k})) AS j) GROUP BY j)"
    for s in range(steps):
        out += f""", l{s} AS (SELECT list(pow(0, 0) * ca ORDER BY c) AS ca, list(cb ORDER BY c) AS cb FROM k{s}),
n{s} AS (SELECT a, b, [{", ".join(f"pow(a - ca[{i + 1}], 2) + pow(b - cb[{i + 1}], 2)" for i in range(k))}] AS far FROM p, l{s}),
k{s + 1} AS (SELECT list_position(far, list_min(far)) - 1 AS c, avg(a) AS ca, avg(b) AS cb FROM n{s} GROUP BY 1)"""
    return out + f" SELECT CAST(c AS INTEGER) AS seed, round(ca, 6) AS instability, round(cb, 6) AS extreme FROM k{steps}"


@query("kmeans_lloyd", _lloyd_sql(5))
def kmeans_lloyd(spark, d):
    """Five steps from quantile seeds, against the same steps unrolled in SQL."""
    return _rows(spark, P.kmeans(_features(spark, d), 5, how="quantile", iterations=5, tolerance=-1))


@query("kmeans_converged")
def kmeans_converged(spark, d):
    """Lloyd from range seeds until nothing moves; centres named in order."""
    got = P.named(P.kmeans(_features(spark, d)), version=1)
    return spark.createDataFrame([(c.version, c.cluster, c.center[0], c.center[1], c.rank, c.label) for c in got], "version int, cluster int, instability double, extreme double, rank int, label string")


def _vectors(df, cols):
    from pyspark.ml.feature import VectorAssembler

    return VectorAssembler(inputCols=list(cols), outputCol="features").transform(df)


def _mllib(spark, d, make):
    v = _vectors(_features(spark, d), P.FEATURES)
    model = make.fit(v)
    return model, model.transform(v)


@query("kmeans_mllib")
def kmeans_mllib(spark, d):
    from pyspark.ml.clustering import KMeans

    model, out = _mllib(spark, d, KMeans(k=5, seed=42, maxIter=50))
    return out.groupBy("prediction").agg(F.count(F.lit(1)).alias("windows"), F.avg("extreme").alias("extreme"), F.avg("instability").alias("instability")).withColumn("objective", F.lit(model.summary.trainingCost))


@query("bisecting_kmeans")
def bisecting_kmeans(spark, d):
    from pyspark.ml.clustering import BisectingKMeans

    _, out = _mllib(spark, d, BisectingKMeans(k=5, seed=42))
    return out.groupBy("prediction").agg(F.count(F.lit(1)).alias("windows"), F.avg("extreme").alias("extreme"))


@query("gaussian_mixture")
def gaussian_mixture(spark, d):
    from pyspark.ml.clustering import GaussianMixture

    _, out = _mllib(spark, d, GaussianMixture(k=3, seed=42, maxIter=20))
    return out.groupBy("prediction").agg(F.count(F.lit(1)).alias("windows"), F.avg("extreme").alias("extreme"))


@query("supervised_tree")
def supervised_tree(spark, d):
    """A small tree trained on labels of four fifths of the windows; accuracy on the rest."""
    from pyspark.ml.classification import DecisionTreeClassifier

    v = _vectors(labelled_windows(spark, d).withColumn("y", F.col("rank").cast("double")), P.FEATURES)
    model = DecisionTreeClassifier(labelCol="y", maxDepth=6).fit(v.where("event_id % 5 <> 0"))
    return model.transform(v.where("event_id % 5 = 0")).agg(F.count(F.lit(1)).alias("windows"), F.avg((F.col("prediction") == F.col("y")).cast("double")).alias("accuracy"))


_D0 = "list_min(far)"


@query("kmeans_objective", L.replace("WITH", "WITH", 1) + " SELECT round(sum(list_min(far)), 4) AS objective, count(*) AS windows FROM ds")
def kmeans_objective(spark, d):
    f = _features(spark, d)
    return f.agg(F.round(P.objective(f, [c.center for c in P.VERSION_0]), 4).alias("objective"), F.count(F.lit(1)).alias("windows"))


@query("elbow_curve")
def elbow_curve(spark, d):
    """Objective for k = 2..8 and whether k is the knee."""
    f = stored(_features(spark, d).select(*P.FEATURES), "features")
    js: dict[int, float] = {}
    for k in range(2, 9):
        fits = [P.kmeans(f, k, how=how, iterations=10) for how in ("quantile",)]
        js[k] = min(f.agg(P.objective(f, c).alias("j")).first()["j"] for c in fits)
    knee = P.elbow(js)
    return spark.createDataFrame([(k, j, k == knee) for k, j in js.items()], "k int, objective double, knee boolean")


@query("label_profiles", f"{L}, t AS (SELECT avg(instability) AS i, avg(extreme) AS e, count(*) AS n FROM lw GROUP BY rank) SELECT CAST(row_number() OVER (ORDER BY e, i) - 1 AS INTEGER) AS rank, ['Calm', 'Moderate', 'Slightly Unstable', 'Aggressive', 'Very Aggressive'][row_number() OVER (ORDER BY e, i)] AS label, n AS windows, round(100e0 * n / sum(n) OVER (), 4) AS percent FROM t")
def label_profiles(spark, d):
    """The profile table of the labelled windows: the clusters' centres, named again. A row a cluster comes to the driver."""
    rows = labelled_windows(spark, d).groupBy("rank").agg(F.avg("instability").alias("i"), F.avg("extreme").alias("e"), F.count(F.lit(1)).alias("n")).collect()
    size, total = {(r["i"], r["e"]): r["n"] for r in rows}, sum(r["n"] for r in rows)
    return spark.createDataFrame([(c.rank, c.label, size[c.center], round(100.0 * size[c.center] / total, 4)) for c in P.named(list(size))], "rank int, label string, windows long, percent double")


@query("label_other_domain", f"WITH {C.LINEITEM_SQL}, s AS (SELECT vehicle_id, win_start, var_pop(sqrt(x*x+y*y+z*z)) AS i, sqrt(pow(quantile_cont(x, 0.99), 2) + pow(quantile_cont(y, 0.99), 2) + pow(quantile_cont(z, 0.99), 2)) AS e FROM li GROUP BY 1, 2), f AS (SELECT *, [abs(e - 40), abs(e - 60), abs(e - 70)] AS far FROM s) SELECT ['Healthy', 'Worn', 'Failing'][list_position(far, list_min(far))] AS label, count(*) AS windows, round(avg(e), 5) AS mean_extreme FROM f GROUP BY 1")
def label_other_domain(spark, d):
    """Three machine-health levels over the lineitem carrier, one feature."""
    s = edge.summarize(C.lineitem_samples(spark, d), stats="peaks").withColumn("extreme", edge.extreme())
    named = P.named([(40.0,), (60.0,), (70.0,)], P.MACHINE, order=(0,))
    return P.assign(s, named, ("extreme",)).groupBy("label").agg(F.count(F.lit(1)).alias("windows"), F.round(F.avg("extreme"), 5).alias("mean_extreme"))


@query("assign_profiles", f"{L} SELECT event_id, rank, label, 0 AS version FROM lw")
def assign_profiles(spark, d):
    s = summaries(spark, d).select("event_id", edge.extreme().alias("extreme"), F.col("mag_var").alias("instability"))
    return P.assign(s, P.VERSION_0).select("event_id", "rank", "label", "version")


def save_centroids(spark, path: str, centroids: list[P.Centroid]) -> None:
    """Append a version to the registry; versions are never rewritten."""
    rows = [(c.version, c.cluster, list(c.center), c.rank, c.label) for c in centroids]
    spark.createDataFrame(rows, "version int, cluster int, center array<double>, rank int, label string").coalesce(1).write.mode("append").parquet(path)


def load_centroids(spark, path: str, version: int | None = None) -> list[P.Centroid]:
    """One version, the latest by default. A registry version has K rows."""
    t = spark.read.parquet(path)
    v = t.agg(F.max("version").alias("v")).first()["v"] if version is None else version
    return [P.Centroid(r["cluster"], tuple(r["center"]), r["rank"], r["label"], v) for r in t.where(F.col("version") == v).orderBy("cluster").collect()]


def refresh_due(last_built_s: int, now_s: int, every_s: int, drift: float = 0.0, limit: float = 0.2) -> bool:
    """Whether profiles are to be built again: by schedule, or because distributions moved."""
    return now_s - last_built_s >= every_s or drift > limit


@query("centroid_registry")
def centroid_registry(spark, d):
    path = f"{shared_dir(spark)}/registry-{uuid.uuid4().hex}"
    save_centroids(spark, path, P.VERSION_0)
    save_centroids(spark, path, P.named(P.kmeans(_features(spark, d), iterations=10), version=1))
    return spark.read.parquet(path).groupBy("version").agg(F.count(F.lit(1)).alias("centroids"), F.array_sort(F.collect_set("label")).alias("labels")).withColumn("latest", F.col("version") == F.lit(load_centroids(spark, path)[0].version))


_WEEK = "win_start < 1704672000"


@query("drift_detection", f"{L}, r AS (SELECT min(extreme) AS lo, (max(extreme) - min(extreme)) / 10 AS w FROM lw WHERE {_WEEK}), b AS (SELECT CAST(greatest(0, least(9, floor((extreme - lo) / w))) AS INTEGER) AS bin, {_WEEK} AS ref FROM lw, r), s AS (SELECT bin, count(*) FILTER (ref) / (SELECT count(*) FILTER (ref) FROM b) AS rs, count(*) FILTER (NOT ref) / (SELECT count(*) FILTER (NOT ref) FROM b) AS cs FROM b GROUP BY bin) SELECT bin, round(rs, 6) AS ref_share, round(cs, 6) AS cur_share, round((greatest(cs, 1e-6) - greatest(rs, 1e-6)) * ln(greatest(cs, 1e-6) / greatest(rs, 1e-6)), 6) AS part FROM s")
def drift_detection(spark, d):
    f = _features(spark, d)
    ref, cur = f.where(_WEEK), f.where(f"not ({_WEEK})")
    r = ref.agg(F.min("extreme").alias("lo"), F.max("extreme").alias("hi")).first()
    return P.psi(ref, cur, "extreme", r["lo"], r["hi"]).select("bin", F.round("ref_share", 6).alias("ref_share"), F.round("cur_share", 6).alias("cur_share"), F.round("part", 6).alias("part"))


@query("drift_centroid_shift", f"{L}, s AS (SELECT label, count(*) FILTER ({_WEEK}) AS ref_windows, count(*) FILTER (NOT ({_WEEK})) AS cur_windows, avg(instability) FILTER ({_WEEK}) AS ri, avg(instability) FILTER (NOT ({_WEEK})) AS ci, avg(extreme) FILTER ({_WEEK}) AS re, avg(extreme) FILTER (NOT ({_WEEK})) AS ce FROM lw GROUP BY label) SELECT label, round(sqrt((ci - ri) * (ci - ri) + (ce - re) * (ce - re)), 6) AS shift, round(ref_windows * 1e0 / sum(ref_windows) OVER (), 6) AS ref_share, round(cur_windows * 1e0 / sum(cur_windows) OVER (), 6) AS cur_share FROM s")
def drift_centroid_shift(spark, d):
    """By profile: how far the mean of its windows has moved since the reference week, and its share of the windows then and now."""
    moved = P.shift(labelled_windows(spark, d), F.expr(_WEEK))
    return moved.select("label", *[F.round(c, 6).alias(c) for c in ("shift", "ref_share", "cur_share")])


@query("cluster_profile", f"{L} SELECT label, rank, count(*) AS windows, round(count(*) / (SELECT count(*) FROM lw), 6) AS share, round(avg(instability), 6) AS mean_instability, round(avg(extreme), 6) AS mean_extreme FROM lw GROUP BY 1, 2")
def cluster_profile(spark, d):
    p = P.profile(labelled_windows(spark, d))
    return p.select("label", "rank", "windows", F.round("share", 6).alias("share"), F.round("mean_instability", 6).alias("mean_instability"), F.round("mean_extreme", 6).alias("mean_extreme"))


@query("imbalance_ratio", f"{L}, c AS (SELECT count(*) AS n FROM lw GROUP BY label) SELECT CAST(max(n) AS BIGINT) AS largest, CAST(min(n) AS BIGINT) AS smallest, round(max(n) / min(n), 6) AS ratio FROM c")
def imbalance_ratio(spark, d):
    n = labelled_windows(spark, d).groupBy("label").count()
    return n.agg(F.max("count").alias("largest"), F.min("count").alias("smallest"), F.round(F.max("count") / F.min("count"), 6).alias("ratio"))


@query("centroid_separation", f"{L}, c AS (SELECT rank AS c, avg(instability) AS i, avg(extreme) AS e FROM lw GROUP BY 1) SELECT a.c AS a, b.c AS b, round(sqrt(pow(a.i - b.i, 2) + pow(a.e - b.e, 2)), 6) AS distance FROM c a JOIN c b ON a.c < b.c")
def centroid_separation(spark, d):
    """Distances between the centres of the labelled windows' profiles."""
    c = labelled_windows(spark, d).groupBy(F.col("rank").alias("a")).agg(F.avg("instability").alias("i"), F.avg("extreme").alias("e"))
    o = c.toDF("b", "i2", "e2")
    return c.join(F.broadcast(o), F.col("a") < F.col("b")).select("a", "b", F.round(F.sqrt(F.pow(F.col("i") - F.col("i2"), 2) + F.pow(F.col("e") - F.col("e2"), 2)), 6).alias("distance"))


@query("silhouette", f"{L}, st AS (SELECT rank AS c, count(*) AS n, sum(instability*instability + extreme*extreme) AS q, sum(instability) AS si, sum(extreme) AS se FROM lw GROUP BY 1), t AS (SELECT lw.event_id, lw.rank, st.c, st.n, st.n * (instability*instability + extreme*extreme) + st.q - 2 * (instability * st.si + extreme * st.se) AS tot FROM lw CROSS JOIN st), ab AS (SELECT event_id, min(tot / (n - 1)) FILTER (c = rank AND n > 1) AS a, min(tot / n) FILTER (c <> rank) AS b FROM t GROUP BY event_id) SELECT round(avg(CASE WHEN a IS NULL THEN 0 ELSE (b - a) / greatest(a, b) END), 6) AS silhouette FROM ab")
def silhouette(spark, d):
    return P.silhouette(labelled_windows(spark, d), cluster="rank").select(F.round("silhouette", 6).alias("silhouette"))


@query("silhouette_mllib")
def silhouette_mllib(spark, d):
    from pyspark.ml.evaluation import ClusteringEvaluator

    v = _vectors(labelled_windows(spark, d).withColumn("prediction", F.col("rank").cast("int")), P.FEATURES)
    return spark.createDataFrame([(float(ClusteringEvaluator(metricName="silhouette").evaluate(v)),)], "silhouette double")


_PAIRWISE = f"{L}, s AS (SELECT event_id, rank, instability, extreme FROM lw ORDER BY (event_id * 7919) % 10007, event_id LIMIT 400), t AS (SELECT x.event_id, x.rank, y.rank AS o, avg(sqrt(pow(x.instability - y.instability, 2) + pow(x.extreme - y.extreme, 2))) AS far FROM s x JOIN s y ON x.event_id <> y.event_id GROUP BY 1, 2, 3), ab AS (SELECT event_id, min(far) FILTER (o = rank) AS a, min(far) FILTER (o <> rank) AS b FROM t GROUP BY 1) SELECT round(avg(CASE WHEN a IS NULL THEN 0 ELSE (b - a) / greatest(a, b) END), 6) AS silhouette, count(*) AS points FROM ab"


#: Most places of a cell of the all-pairs silhouette, and cells (about) after which cells take more: the driver holds them.
_BLOCK, _CELLS = 1024, 16384
#: Most places of the leaves that a task takes at once, those near them not counted.
_GROUP = 65536


#: Rows of the tiles of two blocks whose distances are held at once.
_TILE = distances.TILE


def _block_distances(batches):
    """Summed distances of each row of two blocks to the rows of each rank in the other; within one block once. The form without cells, for blocks that are given whole."""
    import numpy as np
    import pyarrow as pa

    def part(block):
        """ids, ranks and features in order of rank, and where each rank starts."""
        i, r, *f = (block.field(c).to_numpy(zero_copy_only=False) for c in ("event_id", "rank", "instability", "extreme"))
        order = np.argsort(r, kind="stable")
        ranks, first = np.unique(r[order], return_index=True)
        return i[order], r[order], *(c[order] for c in f), ranks, [*first, len(r)]

    def tiles(bounds, size):
        return [(k, i, min(i + size, bounds[k + 1])) for k in range(len(bounds) - 1) for i in range(bounds[k], bounds[k + 1], size)]

    def sums(ids, ranks, others, total):
        for k, o in enumerate(others):
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(ranks, pa.int32()), pa.array(np.full(len(ids), o), pa.int32()), pa.array(total[k], pa.float64())], names=["event_id", "rank", "o_rank", "far"])

    room = np.empty((2, _TILE[0] * _TILE[1]))
    for batch in batches:
        for n in range(batch.num_rows):
            same = batch.column("x")[n].as_py() == batch.column("y")[n].as_py()
            (xi, xr, xa, xb, xo, xs), (yi, yr, ya, yb, yo, ys) = (part(batch.column(c)[n].values) for c in ("x_rows", "y_rows"))
            to_y, to_x = np.zeros((len(yo), len(xi))), np.zeros((len(xo), len(yi)))
            for kx, i, j in tiles(xs, _TILE[0]):
                for ky, p, q in tiles(ys, _TILE[1]):
                    far = distances.between(xa[i:j], xb[i:j], ya[p:q], yb[p:q], room)
                    to_y[ky, i:j] += far.sum(axis=1)
                    if not same:
                        to_x[kx, p:q] += far.sum(axis=0)
            yield from sums(xi, xr, yo, to_y)
            if not same:
                yield from sums(yi, yr, xo, to_x)


def _far_silhouettes(s, low, high, ranks, size, odd):
    """rank, n, a and b (distances.silhouette_parts) of the finite places s."""
    import numpy as np
    import pyarrow as pa

    spark, places = s.sparkSession, s.count()

    def cell(scale):
        return [F.floor(F.col(c) * F.lit(scale)).alias(c2) for c, c2 in (("a", "x"), ("b", "y"))]

    def count(scale, kept, scale_kept):
        p = s.select(*cell(scale), *[c.alias(f"k{n}") for n, c in zip("xy", cell(scale_kept or scale), strict=True)])
        if kept is not None:
            p = p.join(F.broadcast(spark.createDataFrame(pa.table(kept, names=["kx", "ky"]))), ["kx", "ky"], "left_semi")
        got = p.groupBy("x", "y").agg(F.count(F.lit(1)).alias("n")).toArrow()
        return tuple(got.column(c).to_numpy() for c in ("x", "y", "n"))

    cells = distances.Cells(low, high, max(_BLOCK, -(-places // _CELLS)), count)
    tree = spark.sparkContext.broadcast(cells)
    parts = max(1, -(-places // _GROUP))
    packed = s.mapInArrow(lambda b: distances.leaf_rows(b, tree), "leaf long, rank int, a double, b double, n long")
    packed = stored(packed.repartition(parts, "leaf").sortWithinPartitions("leaf", "rank"), "leaves")
    got = packed.mapInArrow(lambda b: distances.leaf_charges(b, tree), "leaf long, rank int, charge binary").toArrow()
    charges = np.frombuffer(b"".join(got.column("charge").to_pylist())).reshape(-1, distances.NODES, distances.NODES)
    cells.charge(got.column("leaf").to_numpy(), np.searchsorted(ranks, got.column("rank").to_numpy()), charges)
    near = cells.near()
    # leaves that follow each other make a group, by places and by pairs
    upto = np.concatenate([[0], np.cumsum(cells.places)])
    cost = cells.places * np.array([sum(upto[q] - upto[p] for p, q in n) + 8 * distances.NODES**2 for n in near])
    group = np.maximum(upto[1:] // min(_GROUP, max(2048, -(-places // 24))), np.cumsum(cost) * 3 * parts // max(1, cost.sum()))
    group = np.cumsum(np.concatenate([[0], np.diff(group) > 0]))
    needs = {(leaf, int(group[own])) for own, n in enumerate(near) for p, q in n for leaf in range(p, q)}
    needs = spark.createDataFrame(pa.table(np.array(sorted(needs)).T.tolist(), names=["leaf", "grp"]))
    tree, near, of = (spark.sparkContext.broadcast(x) for x in (cells, near, group))
    sent = packed.join(F.broadcast(needs), "leaf").repartition(int(group[-1]) + 1, "grp").sortWithinPartitions("grp", "leaf")
    return sent.mapInArrow(lambda b: distances.silhouette_parts(b, tree, of, near, ranks, size, odd), "rank int, n long, a double, b double")


def pairwise_silhouette(w):
    """silhouette and points: Euclidean, over all pairs of the rows of w (rank, features): rows of one place and rank at once, near places pair by pair, far ones cell by cell."""
    import numpy as np

    s = stored(w.groupBy(F.col("rank").cast("int").alias("rank"), F.col("instability").alias("a"), F.col("extreme").alias("b")).agg(F.count(F.lit(1)).alias("n")), "places")
    finite = F.coalesce((F.abs("a") < float("inf")) & (F.abs("b") < float("inf")), F.lit(False))
    ends = [f(F.when(finite, F.col(c))).alias(f"{f.__name__}_{c}") for f in (F.min, F.max) for c in ("a", "b")]
    known = F.isnotnull("a") & F.isnotnull("b") & ~F.isnan("a") & ~F.isnan("b")
    got = s.groupBy("rank").agg(F.sum("n").alias("n"), F.count_if(finite).alias("finite"), F.count_if(~known).alias("unknown"), F.count_if(known & ~finite).alias("endless"), *ends).orderBy("rank").collect()  # one row a rank
    ranks, size = np.array([r["rank"] for r in got]), np.array([r["n"] for r in got])
    odd = np.array([math.nan if r["unknown"] else math.inf if r["endless"] else 0.0 for r in got])
    of = F.create_map(*[F.lit(v) for r in got for v in (r["rank"], r["n"])]) if got else F.lit(None)
    none = F.lit(math.nan)  # distances from a place that is not finite
    t = s.where(~finite).select("rank", "n", F.when(of[F.col("rank")] > 1, none).alias("a"), (none if len(got) > 1 else F.lit(None).cast("double")).alias("b")) if got else s.select("rank", "n", "a", "b")
    if any(r["finite"] for r in got):
        low, high = ([pick(r[f"{f}_{c}"] for r in got if r["finite"]) for c in ("a", "b")] for f, pick in (("min", min), ("max", max)))
        t = t.unionByName(_far_silhouettes(s.where(finite), low, high, ranks, size, odd))
    value = F.when(F.col("a").isNull(), 0.0).otherwise(F.try_divide(F.col("b") - F.col("a"), F.greatest("a", "b")))
    t = t.withColumn("value", value)
    return t.agg(F.round(F.sum(F.col("value") * F.col("n")) / F.sum(F.when(F.col("value").isNotNull(), F.col("n"))), 6).alias("silhouette"), F.coalesce(F.sum("n"), F.lit(0)).alias("points"))


@query("silhouette_exact")
def silhouette_exact(spark, d):
    """Euclidean silhouette over all pairs of all windows."""
    return pairwise_silhouette(labelled_windows(spark, d))


@query("silhouette_exact_400", _PAIRWISE)
def silhouette_exact_400(spark, d):
    """The same method over the 400 windows that its SQL covers."""
    return pairwise_silhouette(labelled_windows(spark, d).orderBy(F.pmod(F.col("event_id") * 7919, F.lit(10007)), "event_id").limit(400))


@query("embedding_kmeans")
def embedding_kmeans(spark, d):
    """General-dimension K-Means over embeddings: clusters against reference classes, with purity."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = C.table(spark, d, "embeddings").select("vec_id", "label", array_to_vector(F.col("embedding").cast("array<double>")).alias("features"))
    out = KMeans(k=10, seed=42, maxIter=30).fit(v).transform(v)
    cells = out.groupBy("prediction", "label").agg(F.count(F.lit(1)).alias("n"))
    return cells.groupBy("prediction").agg(F.sum("n").alias("vectors"), (F.max("n") / F.sum("n")).alias("purity"))


@query("embedding_confusion", "SELECT label, count(*) AS vectors, round(avg(list_inner_product(list_transform(embedding, lambda x: CAST(x AS DOUBLE)), list_transform(embedding, lambda x: CAST(x AS DOUBLE)))), 4) AS mean_square FROM embeddings GROUP BY label")
def embedding_confusion(spark, d):
    sq = F.aggregate(F.col("embedding").cast("array<double>"), F.lit(0.0), lambda a, x: a + x * x)
    return C.table(spark, d, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("vectors"), F.round(F.avg(sq), 4).alias("mean_square"))


@query("rule_thresholds", f"{L} SELECT CASE WHEN extreme < 10.6e0 THEN 'Calm' WHEN extreme < 11.2e0 THEN 'Moderate' WHEN extreme < 12e0 THEN 'Slightly Unstable' WHEN extreme < 13.3e0 THEN 'Aggressive' ELSE 'Very Aggressive' END AS rule, label, count(*) AS windows FROM lw GROUP BY 1, 2")
def rule_thresholds(spark, d):
    return labelled_windows(spark, d).groupBy(P.rules().alias("rule"), "label").agg(F.count(F.lit(1)).alias("windows"))


_EPS, _MIN = 0.05, 8


@query("density_core_points")
def density_core_points(spark, d):
    """Neighbours within eps (itself included) of every window, and whether they make it a core point."""
    return _cores(labelled_windows(spark, d))


@query("density_core_points_every_10th", f"{L}, s AS (SELECT event_id, instability AS a, extreme AS b FROM lw WHERE event_id % 10 = 0) SELECT x.event_id, count(*) AS neighbours, count(*) >= {_MIN} AS core FROM s x JOIN s y ON pow(x.a - y.a, 2) + pow(x.b - y.b, 2) <= {_EPS * _EPS}e0 GROUP BY 1")
def density_core_points_every_10th(spark, d):
    """The same method over the windows that its SQL covers."""
    return _cores(labelled_windows(spark, d).where("event_id % 10 = 0"))


#: Cells are a little wider than eps, so that rounding never puts a neighbour two cells away.
_SIDE = _EPS * 1.001


def _points(w, parts, side=_SIDE):
    """event_id, a, b, and a box (fa, fb), of which parts x parts make a cell."""
    return w.select("event_id", F.col("instability").alias("a"), F.col("extreme").alias("b")).withColumns({"fa": F.floor(F.col("a") * parts / side), "fb": F.floor(F.col("b") * parts / side)})


def _boxes(p):
    """fa, fb, the number of points and the bounds that they take up."""
    return p.groupBy("fa", "fb").agg(F.count(F.lit(1)).alias("n"), F.min("a").alias("a0"), F.max("a").alias("a1"), F.min("b").alias("b0"), F.max("b").alias("b1"))


def _far(a0, a1, b0, b1, most):
    """Largest or smallest squared distance between bounds (a0, a1, b0, b1) and the other box's (oa0, oa1, ob0, ob1)."""
    out = None
    for lo, hi, lo2, hi2 in ((a0, a1, "oa0", "oa1"), (b0, b1, "ob0", "ob1")):
        gap = F.greatest(F.col(hi) - F.col(lo2), F.col(hi2) - F.col(lo)) if most else F.greatest(F.lit(0.0), F.col(lo2) - F.col(hi), F.col(lo) - F.col(hi2))
        out = gap * gap if out is None else out + gap * gap
    return out


def _box_pairs(boxes, parts, ring=1):
    """Pairs of boxes in cells at most ring apart that may hold neighbours, and whether all their points are."""
    cells = lambda by: {f"c{x}": F.floor(F.col(f"{by}{x}") / parts) for x in "ab"}
    o = boxes.toDF("ofa", "ofb", "on", "oa0", "oa1", "ob0", "ob1").withColumns(cells("of"))
    o = o.withColumn("ca", F.explode(F.array(*[F.col("ca") + i for i in range(-ring, ring + 1)]))).withColumn("cb", F.explode(F.array(*[F.col("cb") + i for i in range(-ring, ring + 1)])))
    near = boxes.withColumns(cells("f")).join(o, ["ca", "cb"]).where(_far("a0", "a1", "b0", "b1", False) <= _EPS * _EPS)
    return near.withColumn("full", _far("a0", "a1", "b0", "b1", True) <= _EPS * _EPS)


def _cores(w):
    """event_id, neighbours, core. Boxes wholly within eps add their counts; points meet only those of boxes that eps cuts.

    The boxes get smaller with the fullest cell, so that a point meets about the 2/3 power of its neighbours.
    """
    fullest = _points(w, 1).groupBy("fa", "fb").count().agg(F.max("count").alias("n")).first()["n"] or 1
    parts = max(1, round(fullest ** (1 / 3) / 2))
    p = stored(_points(w, parts), "points")
    pairs = stored(_box_pairs(_boxes(p), parts), "pairs")
    whole = p.join(pairs.where("full").groupBy("fa", "fb").agg(F.sum("on").alias("k")), ["fa", "fb"]).select("event_id", "k")
    cut = p.join(pairs.where("NOT full").select("fa", "fb", "ofa", "ofb", "on", "oa0", "oa1", "ob0", "ob1"), ["fa", "fb"])
    cut = cut.where(_far("a", "a", "b", "b", False) <= _EPS * _EPS).withColumn("full", _far("a", "a", "b", "b", True) <= _EPS * _EPS)
    in_box = cut.where("full").groupBy("event_id").agg(F.sum("on").alias("k"))
    o = p.toDF("o", "oa", "ob", "ofa", "ofb")
    one = cut.where("NOT full").select("event_id", "a", "b", "ofa", "ofb").join(o, ["ofa", "ofb"]).where(_near()).groupBy("event_id").agg(F.count(F.lit(1)).alias("k"))
    n = whole.unionByName(in_box).unionByName(one).groupBy("event_id").agg(F.sum("k").alias("neighbours"))
    return n.withColumn("core", F.col("neighbours") >= _MIN)


def _near():
    da, db = F.col("a") - F.col("oa"), F.col("b") - F.col("ob")
    return da * da + db * db <= _EPS * _EPS


@query("density_grid")
def density_grid(spark, d):
    """Density clusters of all windows: core points within eps share a cluster."""
    return _density_clusters(labelled_windows(spark, d))


#: Boxes to a side of a clustering cell; the cell's diagonal is under eps.
_PARTS = 8


def _density_clusters(w):
    """cluster (its least core id) and points. All core points of a cell share a cluster, so the least id is passed on
    between cells until nothing changes; two cells touch if a pair of boxes does, else if a pair of their points does."""
    cores = _points(w.join(_cores(w).where("core").select("event_id"), "event_id", "left_semi"), _PARTS, _EPS / 1.5)
    p = stored(cores.withColumns({f"c{x}": F.floor(F.col(f"f{x}") / _PARTS) for x in "ab"}), "cores")
    cells = stored(p.groupBy("ca", "cb").agg(F.min("event_id").alias("event_id"), F.count(F.lit(1)).alias("points")), "cells")
    ids = lambda o: [F.floor(F.col(f"{o}f{x}") / _PARTS).alias(f"{o}c{x}") for x in "ab"]
    between = ["ca", "cb", "oca", "ocb"]
    pairs = stored(_box_pairs(_boxes(p), _PARTS, 2).select("fa", "fb", "ofa", "ofb", "full", *ids(""), *ids("o")).where("ca <> oca OR cb <> ocb"), "pairs")
    sure = pairs.where("full").select(*between).distinct()
    open_ = pairs.join(sure, between, "left_anti").select("fa", "fb", "ofa", "ofb", *between)
    o = p.select(F.col("a").alias("oa"), F.col("b").alias("ob"), F.col("fa").alias("ofa"), F.col("fb").alias("ofb"))
    met = open_.join(p.select("a", "b", "fa", "fb"), ["fa", "fb"]).join(o, ["ofa", "ofb"]).where(_near()).select(*between).distinct()
    ends = sure.unionByName(met).join(cells.select("ca", "cb", "event_id"), ["ca", "cb"]).join(cells.select(F.col("ca").alias("oca"), F.col("cb").alias("ocb"), F.col("event_id").alias("o")), ["oca", "ocb"]).select("event_id", "o")
    edges = stored(ends.unionByName(cells.select("event_id", F.col("event_id").alias("o"))), "edges")
    label = cells.select("event_id", F.col("event_id").alias("cluster"))
    mark = None
    while True:
        passed = edges.join(label.withColumnRenamed("event_id", "o"), "o").groupBy("event_id").agg(F.min("cluster").alias("cluster"))
        hop = passed.join(label.toDF("cluster", "next"), "cluster", "left").select("event_id", F.coalesce("next", "cluster").alias("cluster"))
        label = stored(hop, "label")
        now = label.agg(F.sum("cluster").alias("s")).first()["s"]
        if now == mark:
            return label.join(cells.select("event_id", "points"), "event_id").groupBy("cluster").agg(F.sum("points").alias("points"))
        mark = now


@query("one_class_flag", f"{L}, m AS (SELECT avg(instability) AS m1, avg(extreme) AS m2, var_pop(instability) AS v1, var_pop(extreme) AS v2, covar_pop(instability, extreme) AS c FROM lw WHERE rank <= 1), q AS (SELECT label, rank, sqrt((pow(instability - m1, 2) * v2 - 2 * (instability - m1) * (extreme - m2) * c + pow(extreme - m2, 2) * v1) / (v1 * v2 - c * c)) AS far FROM lw, m), l AS (SELECT quantile_cont(far, 0.99) AS lim FROM q WHERE rank <= 1) SELECT label, count(*) AS windows, count(*) FILTER (far > lim) AS deviant FROM q, l GROUP BY label")
def one_class_flag(spark, d):
    o = P.one_class(labelled_windows(spark, d), F.col("rank") <= 1)
    return o.groupBy("label").agg(F.count(F.lit(1)).alias("windows"), F.count_if("deviant").alias("deviant"))


@query("minority_synthesis")
def minority_synthesis(spark, d):
    """Rare rows doubled by points between each and its nearest other rare row."""
    return oversample(labelled_windows(spark, d), "Very Aggressive")


def oversample(w, label, factor=2):
    """event_id, instability, extreme: factor - 1 points for each row of label, on the way to its nearest other one (ties: least event_id). A row alone under its label has none.

    Rows look in the cells around their own; those whose nearest row there is farther than a cell is wide look again
    in cells of twice the width, until the cells around hold everything.
    """
    rare = stored(w.where(F.col("label") == label).select("event_id", "instability", "extreme"), "rare")
    facts = rare.agg(F.count(F.lit(1)).alias("n"), F.greatest(F.max("instability") - F.min("instability"), F.max("extreme") - F.min("extreme")).alias("span")).first()
    width = (facts["span"] or 0.0) / max(1.0, facts["n"] ** 0.5) or 1.0
    other = rare.toDF("o", "oi", "oe")
    di, de = F.col("instability") - F.col("oi"), F.col("extreme") - F.col("oe")
    todo, found = rare, None
    while True:
        cell = lambda c: F.floor(F.col(c) / width)
        around = other.withColumn("ca", F.explode(F.array(*[cell("oi") + i for i in (-1, 0, 1)]))).withColumn("cb", F.explode(F.array(*[cell("oe") + i for i in (-1, 0, 1)])))
        best = todo.withColumns({"ca": cell("instability"), "cb": cell("extreme")}).join(around, ["ca", "cb"]).where("event_id <> o").groupBy("event_id", "instability", "extreme").agg(F.min(F.struct((di * di + de * de).alias("far"), "o", "oi", "oe")).alias("n"))
        last = width > (facts["span"] or 0.0)
        # A little less than the width, as rounding may move a row over the edge of its cell.
        near = stored(best if last else best.where(F.col("n.far") <= (width * 0.999) ** 2), "near")
        found = near if found is None else found.unionByName(near)
        todo = stored(todo.join(near.select("event_id"), "event_id", "left_anti"), "todo")
        if last or todo.isEmpty():
            break
        width *= 2
    each = found.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(factor - 1)))) if factor > 1 else found.limit(0).withColumn("copy", F.lit(1))
    w = F.pmod(F.col("event_id") * 7919 + (F.col("copy") - 1) * 389, F.lit(1000)) / 1000.0
    return each.select("event_id", (F.col("instability") + w * (F.col("n.oi") - F.col("instability"))).alias("instability"), (F.col("extreme") + w * (F.col("n.oe") - F.col("extreme"))).alias("extreme"))
