"""Queries of the experiment workloads."""

from __future__ import annotations

import random
import time

from pyspark.sql import functions as F

from ..functions import profiles as P
from ..functions import questions as Q
from ..plans.store import labelled_windows
from ..sources import carriers as C
from . import baseline_ops
from .answer_ops import ask, parse, retrieve
from .registry import query

#: The five macro questions, in our words.
MACRO = ["Where does aggressive driving happen?", "Which zone has the longest dwell?", "How many moderate events were there?", "Compare morning and evening efficiency", "What patterns are there around NATION_3?"]
_ROW = "run int, question string, mode string, calls int, tokens_in long, tokens_out long, simulated_seconds double, spark_seconds double, score int"


def runs(spark, d, questions=tuple(MACRO), repeats: int = 3, seed: int = 42, modes=("grounded", "raw")):
    """Every question in every mode, `repeats` times in a seeded random order, no cache: one row a run."""
    plan = [(r, q, m) for r in range(1, repeats + 1) for q in questions for m in modes]
    random.Random(seed).shuffle(plan)
    rows = []
    for r, q, m in plan:
        began = time.perf_counter()
        if m == "grounded":
            a = ask(spark, d, q)
            rows.append((r, q, m, a.calls, a.tokens_in, a.tokens_out, a.model_seconds, time.perf_counter() - began, a.score))
        else:
            log = baseline_ops.answer(spark, d, q, Q.TemplateResponder())[1].agg(F.count(F.lit(1)).alias("calls"), F.sum("tokens_in").alias("i"), F.sum("tokens_out").alias("o"), F.sum("seconds").alias("s")).first()
            rows.append((r, q, m, log["calls"], log["i"], log["o"], log["s"], time.perf_counter() - began, None))
    return spark.createDataFrame(rows, _ROW)


@query("workload_macro_questions")
def workload_macro_questions(spark, d):
    """W1: the five macro questions through ask()."""
    return runs(spark, d, repeats=1, modes=("grounded",)).drop("spark_seconds")


@query("workload_compare_modes")
def workload_compare_modes(spark, d):
    """W2-W4: the five macro questions, three runs each in both modes: runs, means of calls, tokens, cost and simulated latency, the spread of each over the runs, and the reductions."""
    t = runs(spark, d, MACRO, repeats=3).withColumns({"tokens": F.col("tokens_in") + F.col("tokens_out"), "usd": F.col("tokens_in") * 5e-8 + F.col("tokens_out") * 8e-8}).withColumnRenamed("simulated_seconds", "simulated_s").withColumnRenamed("spark_seconds", "spark_s")
    measures = ["calls", "tokens", "usd", "simulated_s", "spark_s"]
    per = t.groupBy("question").pivot("mode", ["grounded", "raw"]).agg(F.count(F.lit(1)).alias("runs"), *[F.avg(c).alias(c) for c in measures], *[(F.max(c) - F.min(c)).alias(f"{c}_spread") for c in measures])
    less = lambda c: F.round(1 - F.col(f"grounded_{c}") / F.col(f"raw_{c}"), 4).alias(f"{c}_reduction")
    return per.select("*", less("tokens"), less("usd"), less("simulated_s"))


def timed(spark, d, text: str, responder: Q.TemplateResponder | None = None) -> list[tuple[str, str, float, bool]]:
    """A grounded answer stage by stage: question, stage, seconds, whether simulated. Parse, retrieve and check are clocked; the model's seconds are those its reply states."""
    clock, rows = time.perf_counter(), []

    def lap(stage: str) -> None:
        nonlocal clock
        rows.append((text, stage, time.perf_counter() - clock, False))
        clock = time.perf_counter()

    q = parse(spark, d, [text])[0]
    lap("parse")
    band = (q["h"]["from"], q["h"]["to"]) if q["h"] and q["intent"] != "efficiency" else None
    facts = retrieve(spark, d, q["intent"], band, q["place"], q["event_id"], q["label"])
    lap("retrieve")
    config = Q.Config.micro() if q["intent"] == "event" else Q.Config.macro()
    reply = (responder or Q.TemplateResponder()).generate(Q.prompt(q["intent"], Q.fact_block(facts), text), config)
    rows.append((text, "model", reply.seconds, True))
    clock = time.perf_counter()
    Q.issues(reply.text, facts, [r["name"] for r in C.landmarks(spark, d).select("name").collect()])
    lap("check")
    return rows


@query("latency")
def latency(spark, d):
    """A1: from question to checked reply for the five macro questions, a row a stage; waits for rate limits are no part of it."""
    return spark.createDataFrame([x for q in MACRO for x in timed(spark, d, q)], "question string, stage string, seconds double, simulated boolean")


@query("latency_measured")
def latency_measured(spark, d):
    """A1a, A2, A5 over a log of three seeded runs of each macro question in grounded mode: mean, least, most and spread of the seconds, with tokens and calls a run."""
    log = runs(spark, d, modes=("grounded",)).withColumn("seconds", F.col("spark_seconds") + F.col("simulated_seconds"))
    spread = [f("seconds").alias(n) for f, n in ((F.avg, "mean_s"), (F.min, "min_s"), (F.max, "max_s"), (F.stddev_samp, "spread"))]
    return log.groupBy("question", "mode").agg(F.count(F.lit(1)).alias("runs"), *spread, F.avg(F.col("tokens_in") + F.col("tokens_out")).alias("tokens"), F.max("calls").alias("most_calls"))


#: The questions whose answers are shown side by side: dwell, count, aggressive.
SHOWN = [MACRO[1], MACRO[2], MACRO[0]]


@query("workload_answer_quality")
def workload_answer_quality(spark, d):
    """W5: the grounded and the raw reply to each shown question, with words about the mechanism, coordinates, and the score that the checks give against the same facts."""
    directory = [r["name"] for r in C.landmarks(spark, d).select("name").collect()]
    rows = []
    for q in parse(spark, d, SHOWN):
        facts = retrieve(spark, d, q["intent"], None, q["place"], q["event_id"], q["label"])
        said = {"grounded": ask(spark, d, q["text"]).text, "raw": baseline_ops.answer(spark, d, q["text"], Q.TemplateResponder())[0]}
        rows += [(q["text"], mode, text, Q.score(sum(Q.issues(text, facts, directory).values()))) for mode, text in said.items()]
    t = spark.createDataFrame(rows, "question string, mode string, reply string, score int")
    return t.withColumns({"jargon": F.regexp_count("reply", F.lit(Q.JARGON)), "coordinates": F.regexp_count("reply", F.lit(r"-?[0-9]+[.][0-9]{3,}")), "chars": F.length("reply")})


@query("workload_edge_mission", f"WITH {C.SUMMARY_SQL} SELECT count(*) AS windows, CAST(sum(n) AS BIGINT) AS samples, round(count(*) * 1584 / 1048576e0, 4) AS raw_mib, round(count(*) * 420 / 1048576e0, 4) AS summary_mib FROM su")
def workload_edge_mission(spark, d):
    """W6: edge aggregation of the carrier, with the bytes of both ways."""
    w = labelled_windows(spark, d).agg(F.count(F.lit(1)).alias("windows"), F.sum("n").alias("samples"))
    return w.select("windows", "samples", F.round(F.col("windows") * 1584 / 1048576.0, 4).alias("raw_mib"), F.round(F.col("windows") * 420 / 1048576.0, 4).alias("summary_mib"))


@query("workload_cluster_report")
def workload_cluster_report(spark, d):
    """W7, W11: profile table with the silhouette and each profile's share."""
    w = labelled_windows(spark, d)
    return P.profile(w).crossJoin(F.broadcast(P.silhouette(w, cluster="rank")))


@query("schedule_lag", "SELECT n_name AS nation, count(*) AS lines, round(avg(datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))), 4) AS mean_days, round(avg(CASE WHEN datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) > 60 THEN 1e0 ELSE 0e0 END), 6) AS late_share FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1 ORDER BY late_share DESC, nation LIMIT 10")
def schedule_lag(spark, d):
    """W14: which routes run late: days from order to shipping by supplier nation, share beyond 60 days, the ten worst."""
    li, o = C.table(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_shipdate"), C.table(spark, d, "orders").select("o_orderkey", "o_orderdate")
    s, n = C.table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), C.table(spark, d, "nation").select("n_nationkey", "n_name")
    days = F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).withColumn("days", days)
    per = j.groupBy(F.col("n_name").alias("nation")).agg(F.count(F.lit(1)).alias("lines"), F.round(F.avg("days"), 4).alias("mean_days"), F.round(F.avg((F.col("days") > 60).cast("double")), 6).alias("late_share"))
    return per.orderBy(F.desc("late_share"), "nation").limit(10)


@query("workload_documents")
def workload_documents(spark, d):
    """W13: the chunk-then-combine strategy over long documents: chunks of 3,000 estimated tokens, five sampled."""
    docs = C.table(spark, d, "documents").select(F.col("doc_id").alias("event_id"), F.lit(0).cast("long").alias("epoch_s"), F.ceil(F.length("text") / 4.0).cast("long").alias("tokens"))
    c = baseline_ops.chunk(docs)
    picked = baseline_ops.pick(c)
    return c.join(F.broadcast(picked), "chunk_id", "left_semi").groupBy("chunk_id").agg(F.count(F.lit(1)).alias("documents"), F.sum("tokens").alias("tokens"))
