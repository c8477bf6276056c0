"""Exact top-k inner products by a Voronoi join.

Largest inner product is nearest neighbour after one more component: with M the
largest norm of the data, (x, sqrt(M*M - x.x)) and (q, 0) are as near as q.x is
large. Pivots, a bounded sample of the data, cut both sides into cells. Each
cell is summed up by its radius, its row count and the k + 1 smallest distances
to its pivot. From these alone every query cell gets a bound within which its k
nearest must lie, so a data cell, and then a single row, is sent only to the query
groups whose bound it can meet. Bounds allow for the rounding of their own sums. Groups are solved locally with exact integer
products: doubles where every product and sum stays below 2**53, 64-bit integers below 2**63,
else Python's integers. Large groups are cut into blocks, each giving its own best k, so
no task holds more than a block of each side, and queries go only to blocks of their group.

Defined cases: vectors that are null or hold a null or non-finite component take
no part; shorter vectors count as padded with zeros; ties go to the smaller
vec_id; a query never meets a row of its own vec_id; rows that repeat a vec_id
are candidates of their own, and of a repeated query id the smallest vector asks; scores beyond
64 bits are given as the largest or smallest 64-bit number, and count as ties; components
so large that a norm overflows a double count as the largest whose norm does not.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

#: Pivots are a sample of at most so many rows, whatever the table's size.
PIVOTS = 64
QUERY_GROUP = 512
DATA_BLOCK = 20_000
_SLACK = 1e-6


def scaled(vectors: DataFrame, scale: int = 64) -> DataFrame:
    """vec_id, v: floor(scale * component) of the vectors that take part."""
    widest = F.lit(1e140)
    good = F.col("embedding").isNotNull() & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vectors.where(F.col("vec_id").isNotNull() & good).select("vec_id", F.transform("embedding", lambda x: _floor(F.least(F.greatest(x.cast("double") * scale, -widest), widest))).alias("v"))


def _floor(x):
    """The floor as a double: beyond 2**52 every double is whole already."""
    return F.when(F.abs(x) < float(1 << 52), F.floor(x).cast("double")).otherwise(x)


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat, offsets = column.flatten().to_numpy(zero_copy_only=False), np.asarray(column.offsets)
    sizes = np.diff(offsets)
    out = np.zeros((len(column), width))
    rows = np.repeat(np.arange(len(column)), sizes)
    out[rows, np.arange(len(flat)) - np.repeat(offsets[:-1] - offsets[0], sizes)] = flat
    return out


def _cells(x: np.ndarray, last: np.ndarray, pivots: np.ndarray, pivot_last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nearest pivot and the distance to it, with the added component."""
    square = (x * x).sum(1)[:, None] + (last * last)[:, None] + (pivots * pivots).sum(1) + pivot_last * pivot_last - 2 * (x @ pivots.T + np.outer(last, pivot_last))
    cell = square.argmin(1)
    return cell, np.sqrt(np.maximum(square[np.arange(len(x)), cell], 0))


def nearest(data: DataFrame, queries: DataFrame, k: int = 20, pivots: int = PIVOTS) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k largest integer inner products over data (both vec_id, v)."""
    spark = data.sparkSession
    facts = data.agg(F.max(F.size("v")).alias("width"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("norm2"), F.count(F.lit(1)).alias("n")).first()
    asked = queries.agg(F.max(F.size("v")).alias("width"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("norm2"), F.count(F.lit(1)).alias("n")).first()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if not facts["n"] or not asked["n"]:
        return empty
    width, big = max(facts["width"], asked["width"], 1), float(facts["norm2"])
    slack = _SLACK + float(np.sqrt(16 * (width + 2) * 2.0**-52 * max(big, asked["norm2"])))  # of distances whose squares are rounded
    sample = data.orderBy(F.xxhash64("vec_id"), "vec_id").limit(pivots).collect()
    p = np.zeros((len(sample), width))
    for i, row in enumerate(sample):
        p[i, : len(row["v"])] = row["v"]
    p_last = np.sqrt(np.maximum(big - (p * p).sum(1), 0))
    between = np.sqrt(np.maximum((p * p).sum(1)[:, None] + (p * p).sum(1) - 2 * p @ p.T + (p_last[:, None] - p_last) ** 2, 0))

    def cell_data(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column("v"), width)
            cell, far = _cells(x, np.sqrt(np.maximum(big - (x * x).sum(1), 0)), p, p_last)
            yield pa.RecordBatch.from_pydict({"vec_id": batch.column("vec_id"), "v": batch.column("v"), "cell": cell.astype(np.int32), "far": far})

    def cell_queries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column("v"), width)
            cell, far = _cells(x, np.zeros(len(x)), p, p_last)
            yield pa.RecordBatch.from_pydict({"vec_id": batch.column("vec_id"), "v": batch.column("v"), "cell": cell.astype(np.int32), "far": far})

    kind = "vec_id long, v array<double>, cell int, far double"
    side, ask = common.stored(spark, data.mapInArrow(cell_data, kind), "cells"), common.stored(spark, queries.mapInArrow(cell_queries, kind), "queries")
    # Summaries: a fixed number of cells, each with a few numbers.
    smallest = side.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("far").alias("radius")).collect()
    nth = F.row_number().over(Window.partitionBy("cell").orderBy("far"))  # Spark limits each group before it moves
    near = [(r["cell"], r["far"]) for r in side.select("cell", "far", nth.alias("nth")).where(F.col("nth") <= k + 1).collect()]
    reach = {r["cell"]: r["radius"] for r in ask.groupBy("cell").agg(F.max("far").alias("radius")).collect()}
    heads = {r["cell"]: r["n"] for r in ask.groupBy("cell").count().withColumnRenamed("count", "n").collect()}
    radius = {r["cell"]: r["radius"] for r in smallest}
    groups, load = {}, {}  # query cells into groups of a bounded number of queries
    for c in sorted(heads):
        g = len(load) - 1
        if g < 0 or load[g] + heads[c] > QUERY_GROUP:
            g += 1
        groups[c], load[g] = g, load.get(g, 0) + heads[c]
    routes: dict[int, dict[int, float]] = {}  # data cell -> group -> the distance from its pivot from which on rows are needed
    for c, g in groups.items():
        upper = sorted(reach[c] + between[c, j] + far for j, far in near)[: k + 1]
        bound = (upper[-1] if len(upper) == k + 1 else np.inf) + slack
        for j in radius:
            need = between[c, j] - reach[c] - bound
            if radius[j] + slack >= need:
                at = routes.setdefault(j, {})
                at[g] = min(at.get(g, np.inf), need)
    split = {g: max(1, -(-n // QUERY_GROUP)) for g, n in load.items()}
    rows = [(j, g, float(x)) for j, to in routes.items() for g, x in to.items()]
    route = spark.createDataFrame(rows, "cell int, grp int, need double")
    sent = side.join(F.broadcast(route), "cell").where(F.col("far") + slack >= F.col("need"))
    # As many blocks as the rows that a group is sent need; one number for each group of queries.
    sizes = sent.groupBy("grp").agg(F.count(F.lit(1)).alias("n")).select("grp", F.ceil(F.col("n") / DATA_BLOCK).cast("int").alias("blocks"))
    sizes = common.stored(spark, sizes, "blocks")
    sent = sent.join(F.broadcast(sizes), "grp").select("grp", F.pmod(F.xxhash64("vec_id", "far"), F.col("blocks")).cast("int").alias("block"), "vec_id", "v")
    parts = spark.createDataFrame([(c, g, split[g]) for c, g in groups.items()], "cell int, grp int, cuts int")
    asks = ask.join(F.broadcast(parts), "cell").select("grp", F.pmod(F.xxhash64("vec_id"), F.col("cuts")).cast("int").alias("cut"), "vec_id", "v")
    asks = asks.join(F.broadcast(sizes), "grp").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")
    if max(split.values()) > 1:  # groups of one large cell are cut, and the data goes to each cut
        cuts = spark.createDataFrame([(g, i) for g, n in split.items() for i in range(n)], "grp int, cut int")
        sent = sent.join(F.broadcast(cuts), "grp")
    else:
        sent = sent.withColumn("cut", F.lit(0))

    def solve(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return _BEST.empty_table()
        q, x = _matrix(left["v"], width), _matrix(right["v"], width)
        ids = right["vec_id"].to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, x = ids[order], x[order]
        out = []
        for query, row in zip(left["vec_id"].to_pylist(), q, strict=True):
            score = _products(x, row)
            best = np.flatnonzero(score >= np.partition(score, len(score) - min(k + 1, len(score)))[len(score) - min(k + 1, len(score))])
            best = best[ids[best] != query]
            best = best[np.lexsort((ids[best], ~score[best]))][:k] if len(best) >= k or len(score) <= k + 1 else _again(score, ids, query, k)
            out.append((query, ids[best].tolist(), score[best].tolist()))
        a, b, c = zip(*out, strict=True)
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.list_(pa.int64())), pa.array(c, pa.list_(pa.int64()))], schema=_BEST)

    keys = ["grp", "cut", "block"]
    best = asks.groupBy(*keys).cogroup(sent.groupBy(*keys)).applyInArrow(solve, "query_id long, ids array<long>, scores array<long>")
    return _merge(best, k)


def _products(x: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Exact inner products of whole numbers held as doubles, limited to 64 bits."""
    most = float(np.abs(x).max(initial=0)) * float(np.abs(row).max(initial=0)) * max(1, len(row))
    if most < 2.0**53:
        return (x @ row).astype(np.int64)
    if most < 2.0**62:
        return x.astype(np.int64) @ row.astype(np.int64)
    one = [int(v) for v in row]
    exact = (sum(int(a) * b for a, b in zip(r, one, strict=True) if a) for r in x)
    return np.array([max(-(1 << 63), min((1 << 63) - 1, v)) for v in exact], np.int64)


def _again(score: np.ndarray, ids: np.ndarray, query: int, k: int) -> np.ndarray:
    """The best k where rows of the query's own id crowd the top."""
    own = np.flatnonzero(ids != query)
    return own[np.lexsort((ids[own], ~score[own]))][:k]


_BEST = pa.schema([("query_id", pa.int64()), ("ids", pa.list_(pa.int64())), ("scores", pa.list_(pa.int64()))])


def _merge(best: DataFrame, k: int) -> DataFrame:
    """The blocks' lists of a query, k entries each at most, into its final k."""
    pairs = F.transform(F.arrays_zip("scores", "ids"), lambda x: F.struct(F.bitwise_not(x["scores"]).alias("neg"), x["ids"].alias("vec_id")))
    every = best.groupBy("query_id").agg(F.slice(F.array_sort(F.flatten(F.collect_list(pairs))), 1, k).alias("top"))
    rows = every.select("query_id", F.posexplode("top").alias("pos", "x"))
    return rows.select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), F.bitwise_not(F.col("x.neg")).alias("score"))


def op8_topk(spark, sf_dir: str) -> DataFrame:
    vectors = scaled(common.table(spark, sf_dir, "embeddings"))
    return nearest(vectors, vectors.where(F.col("vec_id") % 20 == 0).groupBy("vec_id").agg(F.min("v").alias("v")), 20)


OP8_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * CAST(x AS DOUBLE))) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 20
"""
