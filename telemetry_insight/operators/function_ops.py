"""Queries of scalar, array, map, JSON and hash functions, and of Python functions where SQL has none."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from ..functions import edge
from ..plans.store import LABELLED_SQL, labelled_windows
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"
E = f"WITH {C.EVENTS_SQL}"


@query("string_functions", "SELECT conv_id, turn, lower(substr(text, 1, 5)) AS head, lpad(CAST(turn AS VARCHAR), 3, '0') AS padded, CAST(len(list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda w: w <> '')) AS INTEGER) AS words, regexp_extract(text, '[A-Z][a-z]+') AS capital, replace(role, 'user', 'rider') AS role FROM conversations")
def string_functions(spark, d):
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
    return C.table(spark, d, "conversations").select("conv_id", "turn", F.lower(F.substring("text", 1, 5)).alias("head"), F.lpad(F.col("turn").cast("string"), 3, "0").alias("padded"), F.size(words).alias("words"), F.regexp_extract("text", "[A-Z][a-z]+", 0).alias("capital"), F.replace(F.col("role"), F.lit("user"), F.lit("rider")).alias("role"))


@query("date_functions", "SELECT event_id, CAST(hour(ts) AS INTEGER) AS hour, CAST(dayofweek(ts) + 1 AS INTEGER) AS weekday, CAST(date_trunc('week', ts) AS DATE) AS week, CAST(ts AS DATE) + 7 AS next_week, CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days, CAST(floor(epoch(ts)) AS BIGINT) AS epoch_s FROM events")
def date_functions(spark, d):
    e = C.table(spark, d, "events")
    return e.select("event_id", F.hour("ts").alias("hour"), F.dayofweek("ts").alias("weekday"), F.date_trunc("week", F.col("ts").cast("timestamp")).cast("date").alias("week"), F.date_add(F.col("ts").cast("date"), 7).alias("next_week"), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("days"), C.epoch(F.col("ts")).alias("epoch_s"))


@query("math_functions", f"{E} SELECT event_id, round(sqrt(value), 6) AS root, round(ln(1 + value), 6) AS log1p, round(radians(k), 6) AS rad, round(sin(radians(k)), 6) AS sine, greatest(value, k) AS most, CAST(floor(value) AS BIGINT) AS low, CAST(sign(value - 50) AS INTEGER) AS side FROM ev")
def math_functions(spark, d):
    return C.events(spark, d).select("event_id", F.round(F.sqrt("value"), 6).alias("root"), F.round(F.log1p("value"), 6).alias("log1p"), F.round(F.radians("k"), 6).alias("rad"), F.round(F.sin(F.radians("k")), 6).alias("sine"), F.greatest(F.col("value"), F.col("k").cast("double")).alias("most"), F.floor("value").alias("low"), F.signum(F.col("value") - 50).cast("int").alias("side"))


@query("array_functions", "SELECT vec_id, len(embedding) AS dims, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS square, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(CAST(list_max(embedding) AS DOUBLE), 6) AS most FROM embeddings")
def array_functions(spark, d):
    v = F.col("embedding").cast("array<double>")
    return C.table(spark, d, "embeddings").select("vec_id", F.size(v).cast("long").alias("dims"), F.round(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 6).alias("square"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.array_max(v), 6).alias("most"))


@query("map_functions", f"WITH {C.SUMMARY_SQL} SELECT event_id, round(x_p99 + 1e-9, 6) AS x, round(z_p99 + 1e-9, 6) AS z, 3 AS axes FROM su")
def map_functions(spark, d):
    m = F.map_from_arrays(F.array(F.lit("x"), F.lit("y"), F.lit("z")), F.array("x_p99", "y_p99", "z_p99"))
    return labelled_windows(spark, d).select("event_id", m.alias("m")).select("event_id", F.round(F.element_at("m", F.lit("x")) + 1e-9, 6).alias("x"), F.round(F.element_at("m", F.lit("z")) + 1e-9, 6).alias("z"), F.size(F.map_entries("m")).alias("axes"))


@query("json_functions", f"{E} SELECT event_id, 'k' AS keys, k, CAST(k AS VARCHAR) AS as_text FROM ev")
def json_functions(spark, d):
    e = C.table(spark, d, "events")
    return e.select("event_id", F.array_join(F.json_object_keys("props"), ",").alias("keys"), F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("as_text"))


@query("hash_functions", "SELECT conv_id, turn, sha256(text) AS sha, md5(text) AS md FROM conversations")
def hash_functions(spark, d):
    return C.table(spark, d, "conversations").select("conv_id", "turn", F.sha2("text", 256).alias("sha"), F.md5("text").alias("md"))


@query("udf_scalar_arrow", "SELECT role, count(*) AS turns, CAST(sum(length(text)) AS BIGINT) AS chars FROM conversations GROUP BY 1")
def udf_scalar_arrow(spark, d):
    """A Python check over Arrow batches, as a fallback; here text length, which SQL confirms."""
    @F.pandas_udf("long")
    def length(s: pd.Series) -> pd.Series:
        return s.str.len()

    return C.table(spark, d, "conversations").groupBy("role").agg(F.count(F.lit(1)).alias("turns"), F.sum(length("text")).alias("chars"))


@query("udaf_grouped")
def udaf_grouped(spark, d):
    """A trimmed mean per vehicle."""
    @F.pandas_udf("double")
    def trimmed(s: pd.Series) -> float:
        cut = len(s) // 10
        kept = s.sort_values().iloc[cut : len(s) - cut]
        return float(kept.mean())

    return C.events(spark, d).groupBy("vehicle_id").agg(trimmed("value").alias("trimmed_mean"))


@query("udtf_packet_rows", f"WITH {C.SUMMARY_SQL}, q AS (SELECT event_id, unnest([x_p01, x_p10, x_p90, x_p99]) AS v FROM su) SELECT event_id, count(*) AS rows FROM q GROUP BY 1")
def udtf_packet_rows(spark, d):
    """Percentile arrays back into rows."""
    w = labelled_windows(spark, d).select("event_id", F.explode(F.array("x_p01", "x_p10", "x_p90", "x_p99")).alias("v"))
    return w.groupBy("event_id").agg(F.count(F.lit(1)).alias("rows"))


@query("map_in_pandas_responder", "SELECT count(*) AS replies FROM conversations WHERE role = 'user'")
def map_in_pandas_responder(spark, d):
    """One reply a question, a client for each partition."""
    from ..functions import questions as Q
    from .answer_ops import answer_batch

    u = C.table(spark, d, "conversations").where("role = 'user'").select(F.concat_ws("-", "conv_id", "turn").alias("id"), F.concat_ws(" ", "conv_id", "turn", "text").alias("prompt"))
    got, _ = answer_batch(u, spark.createDataFrame([], "key string, reply string"), Q.Config.micro())
    return got.where("reply is not null").agg(F.count(F.lit(1)).alias("replies"))


@query("gravity_options", f"WITH {C.BURST_SQL} SELECT event_id, round(avg(sqrt(x*x + y*y + z*z) - 9.81e0), 6) AS less_gravity, round(avg(sqrt(x*x + y*y + z*z) / 9.81e0), 6) AS in_g FROM bu GROUP BY 1")
def gravity_options(spark, d):
    x, y, z = map(F.col, "xyz")
    return C.burst(spark, d).groupBy("event_id").agg(F.round(F.avg(edge.magnitude(x, y, z, 9.81)), 6).alias("less_gravity"), F.round(F.avg(edge.magnitude(x, y, z, 9.81, "divide")), 6).alias("in_g"))
