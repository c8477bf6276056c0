"""Queries of measures: latency, tokens, cost, reductions, projections, wording."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import questions as Q
from ..sources import carriers as C
from .registry import query

#: Published input and output tokens of the grounded answers, and the baseline's tokens and cost (1e-5 USD).
PUBLISHED = [
    ("aggressive driving", 235, 188, 30956, 159.0),
    ("dwell time", 357, 148, 31820, 164.0),
    ("moderate count", 241, 143, 31323, 161.0),
    ("route efficiency", 228, 135, 31423, 162.0),
    ("spatial patterns", 236, 170, 31135, 160.0),
]
_PUB = "pub AS (SELECT * FROM (VALUES " + ", ".join(f"('{q}', {i}, {o}, {b}, {c}e0)" for q, i, o, b, c in PUBLISHED) + ") t(question, tokens_in, tokens_out, baseline_tokens, baseline_cost))"

#: A usage log: run, question, mode, calls, tokens in and out, seconds.
LOG = [(run, q, mode, 1 if mode == "grounded" else 6, i if mode == "grounded" else b - 1500, o if mode == "grounded" else 1500, (0.8 if mode == "grounded" else 17.0) + run * 0.05) for run in (1, 2, 3) for q, i, o, b, _ in PUBLISHED for mode in ("grounded", "raw")]
_LOG = "lg AS (SELECT * FROM (VALUES " + ", ".join(f"({r}, '{q}', '{m}', {c}, {i}, {o}, {s!r}e0)" for r, q, m, c, i, o, s in LOG) + ") t(run, question, mode, calls, tokens_in, tokens_out, seconds))"


def _pub(spark):
    return spark.createDataFrame(PUBLISHED, "question string, tokens_in long, tokens_out long, baseline_tokens long, baseline_cost double")


def _log(spark):
    return spark.createDataFrame(LOG, "run int, question string, mode string, calls long, tokens_in long, tokens_out long, seconds double")


def call_cost(tokens_in="tokens_in", tokens_out="tokens_out", price_in: float = 0.05, price_out: float = 0.08):
    """USD of a call's tokens, prices per million."""
    return F.col(tokens_in) * price_in / 1e6 + F.col(tokens_out) * price_out / 1e6


@query("latency_summary", f"WITH {_LOG} SELECT question, mode, round(avg(seconds), 6) AS mean_s, round(min(seconds), 6) AS min_s, round(max(seconds), 6) AS max_s, round(stddev_samp(seconds), 6) AS spread FROM lg GROUP BY 1, 2")
def latency_summary(spark, d):
    r = lambda c: F.round(c, 6)
    return _log(spark).groupBy("question", "mode").agg(r(F.avg("seconds")).alias("mean_s"), r(F.min("seconds")).alias("min_s"), r(F.max("seconds")).alias("max_s"), r(F.stddev_samp("seconds")).alias("spread"))


@query("token_usage", f"WITH {_LOG} SELECT question, mode, CAST(sum(tokens_in + tokens_out) AS BIGINT) AS tokens FROM lg GROUP BY 1, 2")
def token_usage(spark, d):
    return _log(spark).groupBy("question", "mode").agg(F.sum(F.col("tokens_in") + F.col("tokens_out")).alias("tokens"))


@query("token_estimate", "SELECT conv_id, turn, CAST(ceil(length(text) / 4e0) AS BIGINT) AS tokens FROM conversations")
def token_estimate(spark, d):
    return C.table(spark, d, "conversations").select("conv_id", "turn", F.ceil(F.length("text") / 4.0).cast("long").alias("tokens"))


@query("call_cost", "WITH t AS (SELECT conv_id, role = 'assistant' AS said, CAST(ceil(length(text) / 4e0) AS BIGINT) AS n FROM conversations), c AS (SELECT conv_id, coalesce(sum(n) FILTER (NOT said), 0) AS tokens_in, coalesce(sum(n) FILTER (said), 0) AS tokens_out FROM t GROUP BY 1) SELECT conv_id, round((tokens_in * 0.05e0 + tokens_out * 0.08e0) / 1e6 * 1e5, 4) AS cost_1e5 FROM c")
def call_cost_query(spark, d):
    """What each conversation costs: its replies are the tokens out, all else the tokens in."""
    said, n = F.col("role") == "assistant", F.ceil(F.length("text") / 4.0).cast("long")
    c = C.table(spark, d, "conversations").groupBy("conv_id").agg(F.coalesce(F.sum(F.when(~said, n)), F.lit(0)).alias("tokens_in"), F.coalesce(F.sum(F.when(said, n)), F.lit(0)).alias("tokens_out"))
    return c.select("conv_id", F.round(call_cost() * 1e5, 4).alias("cost_1e5"))


@query("reduction", f"WITH {_PUB} SELECT question, round(100e0 * (1 - (tokens_in + tokens_out) / CAST(baseline_tokens AS DOUBLE)), 4) AS token_percent, round(100e0 * (1 - ((tokens_in * 0.05e0 + tokens_out * 0.08e0) / 1e6 * 1e5) / baseline_cost), 3) AS cost_percent FROM pub")
def reduction(spark, d):
    t = F.col("tokens_in") + F.col("tokens_out")
    return _pub(spark).select("question", F.round(100.0 * (1 - t / F.col("baseline_tokens")), 4).alias("token_percent"), F.round(100.0 * (1 - call_cost() * 1e5 / F.col("baseline_cost")), 3).alias("cost_percent"))


@query("ingest_projection", f"WITH {C.EVENTS_SQL}, m AS (SELECT strftime(make_timestamp(epoch_s * 1000000), '%Y-%m') AS month, count(*) * 1584 / 4e0 AS tokens FROM ev GROUP BY 1) SELECT month, tokens AS tokens_per_month, round(tokens / 1e6 * 30, 4) AS usd_per_month, round(1e6 / (tokens / (30 * 86400e0)), 4) AS seconds_to_fill FROM m")
def ingest_projection(spark, d):
    """If a model read each month's raw telemetry, at four bytes a token: tokens, USD, and seconds until a context of a million is full."""
    month = F.date_format(F.date_from_unix_date(F.floor(F.col("epoch_s") / 86400).cast("int")), "yyyy-MM")
    m = C.events(spark, d).groupBy(month.alias("month")).agg((F.count(F.lit(1)) * 1584 / 4.0).alias("tokens_per_month"))
    tokens = F.col("tokens_per_month")
    return m.select("month", "tokens_per_month", F.round(tokens / 1e6 * 30, 4).alias("usd_per_month"), F.round(1e6 / (tokens / (30 * 86400.0)), 4).alias("seconds_to_fill"))


@query("api_calls", "WITH c AS (SELECT conv_id, max(CASE WHEN role = 'system' THEN 'instructed' ELSE '' END) AS mode, count(*) FILTER (role = 'assistant' AND length(text) > 0) AS calls FROM conversations GROUP BY 1) SELECT CASE mode WHEN '' THEN 'plain' ELSE mode END AS mode, min(calls) AS least, max(calls) AS most FROM c GROUP BY 1")
def api_calls(spark, d):
    """Fewest and most calls (replies) of a conversation, with instructions by the system and without."""
    said = (F.col("role") == "assistant") & (F.length("text") > 0)
    c = C.table(spark, d, "conversations").groupBy("conv_id").agg(F.when(F.max((F.col("role") == "system").cast("int")) == 1, "instructed").otherwise("plain").alias("mode"), F.count_if(said).alias("calls"))
    return c.groupBy("mode").agg(F.min("calls").alias("least"), F.max("calls").alias("most"))


@query("jargon_rate", f"WITH a AS (SELECT conv_id, turn, CAST(len(regexp_extract_all(lower(text), 'chunk|sampled|dataset|in the data provided')) AS INTEGER) AS jargon, CAST(len(regexp_extract_all(text, '-?[0-9]+[.][0-9]{{3,}}')) AS INTEGER) AS coordinates FROM conversations WHERE role = 'assistant') SELECT count(*) AS replies, CAST(sum(jargon) AS BIGINT) AS jargon, CAST(sum(coordinates) AS BIGINT) AS coordinates FROM a".replace("{{", "{").replace("}}", "}"))
def jargon_rate(spark, d):
    """Mechanism words and coordinate strings in replies."""
    a = C.table(spark, d, "conversations").where("role = 'assistant'")
    return a.agg(F.count(F.lit(1)).alias("replies"), F.sum(F.regexp_count("text", F.lit(Q.JARGON))).alias("jargon"), F.sum(F.regexp_count("text", F.lit(r"-?[0-9]+[.][0-9]{3,}"))).alias("coordinates"))


@query("cache_hit_rate", "SELECT count(*) AS asked, count(*) - count(DISTINCT text) AS hits, round((count(*) - count(DISTINCT text)) / count(*), 6) AS rate FROM conversations")
def cache_hit_rate(spark, d):
    c = C.table(spark, d, "conversations").agg(F.count(F.lit(1)).alias("asked"), F.count_distinct("text").alias("called"))
    return c.select("asked", (F.col("asked") - F.col("called")).alias("hits"), F.round((F.col("asked") - F.col("called")) / F.col("asked"), 6).alias("rate"))


@query("prompt_budget", f"WITH {_PUB} SELECT question, tokens_in < 500 AS within_budget FROM pub")
def prompt_budget(spark, d):
    return _pub(spark).select("question", (F.col("tokens_in") < 500).alias("within_budget"))


@query("mission_coverage", "SELECT round(30 * 0.44704e0 * 3, 4) AS metres_per_window, CAST(8040 / 3 AS BIGINT) AS mission_windows")
def mission_coverage(spark, d):
    """What one window covers at 30 miles an hour, and the windows of a mission of 2 h 14 min."""
    return spark.range(1).select(F.round(F.lit(30 * 0.44704 * 3), 4).alias("metres_per_window"), F.lit(2680).cast("long").alias("mission_windows"))
