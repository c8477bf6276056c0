"""Queries of the raw-prompt baseline: keys, chunks, samples, extraction, estimates, limits."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import questions as Q
from ..plans.store import labelled_windows, stored
from ..sources import carriers as C
from .registry import query

BUDGET, CHUNKS = 3000, 5

#: One compact row as the baseline would print it: the telemetry itself under one-letter keys, in thousandths and in 1e-5 degrees.
_KEYS = {"x": ("x", 1000), "y": ("y", 1000), "z": ("z", 1000), "a": ("lat", 100000), "o": ("lon", 100000)}
_ROW_SQL = "'{\"v\":' || vehicle_id || ',\"t\":' || epoch_s || ',\"e\":' || event_id" + "".join(f" || ',\"{k}\":' || CAST(round({c} * {m}) AS BIGINT)" for k, (c, m) in _KEYS.items()) + " || '}'"


def compact(df: DataFrame) -> DataFrame:
    """df with its row text under one-letter keys: vehicle, time, event, the three axes, position."""
    telemetry = [x for k, (c, m) in _KEYS.items() for x in (F.lit(f',"{k}":'), F.round(F.col(c) * m).cast("long"))]
    return df.withColumn("row", F.concat(F.lit('{"v":'), F.col("vehicle_id"), F.lit(',"t":'), F.col("epoch_s"), F.lit(',"e":'), F.col("event_id"), *telemetry, F.lit("}")))


def running_total(df: DataFrame, value: str, order: list[str], parts: int | None = None) -> DataFrame:
    """df with cum, the running sum in a global order: range partitions (as many as the session shuffles to), their totals as offsets, then sums inside each.

    The ranged frame is stored first, so both passes see the same ranges; totals are one row a partition.
    """
    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = stored(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), "ranged")
    totals = ranged.groupBy("_part").agg(F.sum(value).alias("t"))
    before = totals.withColumn("before", F.coalesce(F.sum("t").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("_part", "before")
    inside = F.sum(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return ranged.join(F.broadcast(before), "_part").withColumn("cum", F.col("before") + inside).drop("_part", "before")


def chunk(rows: DataFrame, budget: int = BUDGET) -> DataFrame:
    """rows (tokens, epoch_s, event_id) with chunk_id: consecutive rows of about `budget` tokens."""
    return running_total(rows, "tokens", ["epoch_s", "event_id"]).withColumn("chunk_id", F.floor((F.col("cum") - 1) / budget).cast("long"))


def pick(chunks: DataFrame, m: int = CHUNKS, seed: int = 42, mode: str = "stratified") -> DataFrame:
    """At most m chunk ids spread over the data, one of each of m equal runs of ids.

    Ids grow with the data, so their ranks come from a distributed running sum, and each run is reduced by a partial aggregate.
    """
    ids = chunks.select("chunk_id").distinct()
    mix = F.pmod(F.col("chunk_id") * 7919 + seed, F.lit(10007))
    if mode == "random":
        return ids.orderBy(mix, "chunk_id").limit(m)
    ranked = running_total(ids.withColumn("one", F.lit(1).cast("long")), "one", ["chunk_id"])
    total = ranked.agg(F.max("cum").alias("total"))
    # The first total % m runs hold one id more than the rest.
    short, at = F.floor(F.col("total") / m), F.col("cum") - 1
    long_end = (F.col("total") % m) * (short + 1)
    run = F.when(at < long_end, F.floor(at / (short + 1))).otherwise(F.col("total") % m + F.floor((at - long_end) / F.greatest(short, F.lit(1))))
    key = mix if mode == "stratified" else F.col("chunk_id")
    best = ranked.crossJoin(F.broadcast(total)).groupBy(run.alias("s")).agg(F.min(F.struct(key.alias("key"), "chunk_id")).alias("best"))
    return best.select("best.chunk_id")


def _rows(spark, d):
    e = C.events(spark, d).withColumns(C.fix_columns())
    rank = F.create_map(*[F.lit(x) for p in zip(C.EVENT_TYPES, range(5), strict=True) for x in p])
    return compact(e.withColumns({"x": F.col("value"), "y": F.col("k").cast("double"), "z": rank[F.col("event_type")].cast("double")})).withColumn("tokens", F.ceil(F.length("row") / 4.0).cast("long"))


_ROWS = f"WITH {C.FIX_SQL}{C.NATIVE_SQL.removeprefix(C.EVENTS_SQL)}, te AS (SELECT ev.*, x, y, z, lat, lon FROM ev JOIN na USING (event_id) JOIN fx USING (event_id)), rw AS (SELECT *, {_ROW_SQL} AS row, CAST(ceil(length({_ROW_SQL}) / 4e0) AS BIGINT) AS tokens FROM te), cu AS (SELECT *, sum(tokens) OVER (ORDER BY epoch_s, event_id ROWS UNBOUNDED PRECEDING) AS cum FROM rw), ch AS (SELECT *, CAST(floor((cum - 1) / 3000e0) AS BIGINT) AS chunk_id FROM cu)"
_PICK = _ROWS + ", st AS (SELECT chunk_id, ntile(5) OVER (ORDER BY chunk_id) AS s FROM (SELECT DISTINCT chunk_id FROM ch)), pk AS (SELECT chunk_id FROM (SELECT chunk_id, row_number() OVER (PARTITION BY s ORDER BY (chunk_id * 7919 + 42) % 10007, chunk_id) AS n FROM st) WHERE n = 1)"


@query("shorten_keys", f"{_ROWS} SELECT event_id, length(row) AS chars, tokens FROM rw")
def shorten_keys(spark, d):
    return _rows(spark, d).select("event_id", F.length("row").cast("long").alias("chars"), "tokens")


@query("raw_prompt_direct", f"{_ROWS} SELECT count(*) AS rows, CAST(sum(tokens) AS BIGINT) AS tokens, sum(tokens) <= 128000 AS fits FROM rw")
def raw_prompt_direct(spark, d):
    """Whether all rows fit one prompt of 128,000 tokens."""
    return _rows(spark, d).agg(F.count(F.lit(1)).alias("rows"), F.sum("tokens").alias("tokens"), (F.sum("tokens") <= 128000).alias("fits"))


@query("chunk_rows", f"{_ROWS} SELECT chunk_id, count(*) AS rows, CAST(sum(tokens) AS BIGINT) AS tokens FROM ch GROUP BY 1")
def chunk_rows(spark, d):
    return chunk(_rows(spark, d)).groupBy("chunk_id").agg(F.count(F.lit(1)).alias("rows"), F.sum("tokens").alias("tokens"))


@query("sample_chunks", f"{_PICK} SELECT chunk_id FROM pk")
def sample_chunks(spark, d):
    return pick(chunk(_rows(spark, d)))


@query("sample_chunks_systematic", f"{_ROWS}, st AS (SELECT chunk_id, ntile(5) OVER (ORDER BY chunk_id) AS s FROM (SELECT DISTINCT chunk_id FROM ch)) SELECT min(chunk_id) AS chunk_id FROM st GROUP BY s")
def sample_chunks_systematic(spark, d):
    return pick(chunk(_rows(spark, d)), mode="systematic")


@query("sample_chunks_random", f"{_ROWS} SELECT chunk_id FROM (SELECT DISTINCT chunk_id FROM ch) ORDER BY (chunk_id * 7919 + 42) % 10007, chunk_id LIMIT 5")
def sample_chunks_random(spark, d):
    return pick(chunk(_rows(spark, d)), mode="random")


def answer(spark, d, question: str, responder: Q.TemplateResponder) -> tuple[str, DataFrame]:
    """One call for each sampled chunk, one to combine. The chunks' text comes to the driver, at most CHUNKS budgets of it."""
    chunks = stored(chunk(_rows(spark, d)), "chunks")
    picked = chunks.join(F.broadcast(pick(chunks)), "chunk_id", "left_semi")
    texts = picked.groupBy("chunk_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("epoch_s", "event_id", "row"))), lambda x: x["row"]), "\n").alias("text")).orderBy("chunk_id").collect()
    config, log, parts = Q.Config.macro(), [], []
    for i, r in enumerate(texts):
        reply = responder.generate(f"Extract what matters for: {question}\n\n{r['text']}", config)
        parts.append(reply.text)
        log.append((i, "extract", reply.tokens_in, reply.tokens_out, reply.seconds))
    last = responder.generate(f"Combine the findings for: {question}\n\n" + "\n".join(parts), config)
    log.append((len(log), "combine", last.tokens_in, last.tokens_out, last.seconds))
    return last.text, spark.createDataFrame(log, "call int, kind string, tokens_in int, tokens_out int, seconds double")


@query("extract_then_combine")
def extract_then_combine(spark, d):
    return answer(spark, d, "How many moderate events were there?", Q.TemplateResponder())[1]


@query("sampled_count_estimate", f"{_PICK} SELECT count(*) AS rows_seen, round(count(*) * 1e0 / (SELECT count(*) FROM ch), 6) AS coverage FROM ch WHERE chunk_id IN (SELECT chunk_id FROM pk)")
def sampled_count_estimate(spark, d):
    """How much of the data the sampled chunks see."""
    c = stored(chunk(_rows(spark, d)), "chunks")
    seen = c.join(F.broadcast(pick(c)), "chunk_id", "left_semi").agg(F.count(F.lit(1)).alias("rows_seen"))
    total = c.agg(F.count(F.lit(1)).alias("t"))
    return seen.crossJoin(F.broadcast(total)).select("rows_seen", F.round(F.col("rows_seen") / F.col("t"), 6).alias("coverage"))


@query("count_accuracy")
def count_accuracy(spark, d):
    """Moderate windows: true count, count in the sampled chunks, and that scaled up, with relative errors."""
    c = stored(chunk(_rows(spark, d)), "chunks")
    w = labelled_windows(spark, d).where("label = 'Moderate'").select("event_id")
    seen = c.join(F.broadcast(pick(c)), "chunk_id", "left_semi")
    true, got, part, whole = w.count(), seen.join(w, "event_id", "left_semi").count(), seen.count(), c.count()
    scaled = got * whole / max(1, part)
    return spark.createDataFrame([(true, got, scaled, abs(got - true) / max(1, true), abs(scaled - true) / max(1, true))], "true_count long, sampled_count long, scaled_count double, sampled_error double, scaled_error double")


@query("truncate_to_context", f"{_ROWS} SELECT count(*) FILTER (cum <= 10000) AS kept, count(*) FILTER (cum > 10000) AS lost FROM cu")
def truncate_to_context(spark, d):
    r = running_total(_rows(spark, d), "tokens", ["epoch_s", "event_id"])
    return r.agg(F.count_if(F.col("cum") <= 10000).alias("kept"), F.count_if(F.col("cum") > 10000).alias("lost"))


@query("rate_limit_model", "WITH c AS (SELECT i, sum(t) OVER (ORDER BY i) AS cum FROM (VALUES (1, 3000), (2, 3000), (3, 3000), (4, 3000), (5, 3000), (6, 4000)) v(i, t)) SELECT i AS call, CAST(cum AS BIGINT) AS tokens, greatest((i - 1) * 2e0, floor((cum - 1) / 6000e0) * 60) AS wait_seconds FROM c")
def rate_limit_model(spark, d):
    """When each call may start under 30 calls and 6,000 tokens a minute; reported apart from latency."""
    calls = spark.createDataFrame([(i, t) for i, t in enumerate((3000, 3000, 3000, 3000, 3000, 4000), 1)], "call int, t long")
    cum = F.sum("t").over(Window.orderBy("call").rowsBetween(Window.unboundedPreceding, 0))
    return calls.withColumn("tokens", cum).select("call", "tokens", F.greatest((F.col("call") - 1) * 2.0, F.floor((F.col("tokens") - 1) / 6000.0) * 60).alias("wait_seconds"))
