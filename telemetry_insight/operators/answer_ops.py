"""Queries of fact blocks, prompts, replies, caching and validation; retrieval by intent; the ask() engine."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import analytics as A
from ..functions import questions as Q
from ..plans.store import LABELLED_SQL, labelled_windows
from ..sources import carriers as C
from .intent_ops import W as TEXTS
from .intent_ops import classified_texts
from .registry import query

L = f"WITH {LABELLED_SQL}"


def retrieve(spark: SparkSession, d: str, intent: str, band: tuple[int, int] | None = None, place: str | None = None, event_id: int | None = None, label: str | None = None) -> Q.Facts:
    """The facts of an intent about the profile, place, hours or event asked for: one aggregation over the pre-labelled windows, a handful of rows to the driver."""
    w = labelled_windows(spark, d)
    if band:
        w = w.where(F.col("hour").between(*band))
    if intent == "hotspots":
        own = label or "Aggressive"
        top = A.hotspots(w, (own,)).orderBy(F.desc("events"), "landmark_id").collect()
        return Q.Facts(f"{own} driving events", {"total events": top[0]["total_events"] if top else 0}, [(r["place"], r["events"]) for r in top], own)
    if intent == "dwell":
        rows = A.dwell(w, 43200).orderBy(F.desc("longest"), "place").limit(3).collect()
        return Q.Facts("Longest stays in minutes", {"stays": sum(r["stays"] for r in rows)}, [(r["place"], round(r["longest"], 2)) for r in rows])
    if intent == "count":
        n = (w.where(F.col("label") == label) if label else w).count()
        return Q.Facts(f"{label} driving windows" if label else "All driving windows", {"count": n}, [], label)
    if intent == "efficiency":
        r = A.compare_bands(w).agg(F.sum("morning_events").alias("m"), F.sum("evening_events").alias("e"), F.avg("morning_instability").alias("mi"), F.avg("evening_instability").alias("ei")).first()
        return Q.Facts("Morning against evening", {"morning events": r["m"] or 0, "evening events": r["e"] or 0, "morning instability": round(r["mi"] or 0, 2), "evening instability": round(r["ei"] or 0, 2)}, [])
    if intent == "spatial":
        spots = C.landmarks(spark, d)
        at = (spots.where(F.col("name") == place) if place else spots.orderBy("landmark_id")).first()
        rows = A.around(w, at["lat"], at["lon"]).orderBy(F.desc("windows")).collect()
        return Q.Facts(f"Profiles around {at['name']}", {r["label"]: r["windows"] for r in rows}, [(at["name"], sum(r["windows"] for r in rows))])
    if intent == "event":
        from .micro_ops import context

        return context(spark, d, 17 if event_id is None else event_id)
    return Q.Facts("Supported questions", {}, [])


def parse(spark: SparkSession, d: str, texts: list[str]) -> list:
    """One row a question, in order: intent, place, hours, profile and event number. One job for all."""
    given = spark.createDataFrame(list(enumerate(texts)), "qid int, text string")
    slots = {"h": Q.hours_of(F.col("text")), "label": Q.label_of(F.col("text")), "event_id": Q.event_of(F.col("text"))}
    return Q.place_of(Q.classify(given, Q.lexicon(spark)), C.landmarks(spark, d)).withColumns(slots).orderBy("qid").collect()


def ask_batch(spark: SparkSession, d: str, texts: list[str], responder: Q.TemplateResponder | None = None, cache: Q.Cache | None = None, retries: int = 1, recluster: bool = False) -> list[Q.Answer]:
    """Questions to checked answers; questions of the same intent and slots share their facts. recluster fits profiles first, the cost that stored centroids save."""
    began, known = time.perf_counter(), {}
    directory = [r["name"] for r in C.landmarks(spark, d).select("name").collect()]
    out = []
    for q in parse(spark, d, texts):
        if recluster:
            from ..functions import profiles

            profiles.kmeans(labelled_windows(spark, d).select(*profiles.FEATURES), iterations=20)
        band = (q["h"]["from"], q["h"]["to"]) if q["h"] and q["intent"] != "efficiency" else None
        key = (q["intent"], band, q["place"], q["event_id"], q["label"])
        if key not in known:
            known[key] = retrieve(spark, d, *key)
        out.append(Q.answer(q["text"], q["intent"], known[key], directory, responder or Q.TemplateResponder(), cache, retries, began))
        began = time.perf_counter()
    return out


def ask(spark: SparkSession, d: str, text: str, responder: Q.TemplateResponder | None = None, cache: Q.Cache | None = None, retries: int = 1, recluster: bool = False) -> Q.Answer:
    """A question to a checked answer."""
    return ask_batch(spark, d, [text], responder, cache, retries, recluster)[0]


def _frame(spark, answers: list[Q.Answer]) -> DataFrame:
    return spark.createDataFrame([(a.question, a.intent, a.text, a.score, a.decision, a.tokens_in, a.tokens_out, a.calls, a.model_seconds) for a in answers], "question string, intent string, reply string, score int, decision string, tokens_in int, tokens_out int, calls int, simulated_seconds double")


@query("ask")
def ask_query(spark, d):
    return _frame(spark, ask_batch(spark, d, [t for _, t, _ in Q.QUESTIONS], cache=Q.Cache()))


_FACT = f"""{L}, h AS (SELECT place, landmark_id, count(*) AS n FROM lw WHERE quality = 1 AND label = 'Aggressive' GROUP BY 1, 2),
t AS (SELECT *, row_number() OVER (ORDER BY n DESC, landmark_id) AS i FROM h)
SELECT concat_ws(chr(10), 'Aggressive driving events', '- total events: ' || (SELECT CAST(sum(n) AS BIGINT) FROM h), string_agg(i || '. ' || place || ' (' || n || ')', chr(10) ORDER BY i)) AS block FROM t WHERE i <= 3"""


@query("fact_block", _FACT)
def fact_block(spark, d):
    return spark.createDataFrame([(Q.fact_block(retrieve(spark, d, "hotspots")),)], "block string")


@query("prompt_template")
def prompt_template(spark, d):
    """Prompts of all intents with their estimated tokens, which stay under the budget."""
    rows = [(i, text := Q.prompt(i, Q.fact_block(retrieve(spark, d, i)), q), Q.tokens(text)) for i, q in (("hotspots", "Where?"), ("dwell", "Where do they wait?"), ("count", "How many?"), ("efficiency", "Morning or evening?"), ("spatial", "What is it like around there?"), ("event", "Why did it happen?"))]
    return spark.createDataFrame(rows, "intent string, prompt string, tokens int").withColumn("within_budget", F.col("tokens") < 500)


@query("representation_choice", "SELECT * FROM (VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in Q.REPRESENTATION.items()) + ") t(intent, representation)")
def representation_choice(spark, d):
    return spark.createDataFrame(list(Q.REPRESENTATION.items()), "intent string, representation string")


@query("generation_config", f"{TEXTS} SELECT doc_id, scope, CASE scope WHEN 'macro' THEN 0.7e0 ELSE 0.5e0 END AS temperature, CASE scope WHEN 'macro' THEN 500 ELSE 150 END AS max_tokens FROM cl WHERE score > 0")
def generation_config(spark, d):
    """The settings under which each text with a known intent is answered."""
    macro, micro, own = Q.Config.macro(), Q.Config.micro(), F.col("scope") == "macro"
    return classified_texts(spark, d).where("scope is not null").select("doc_id", "scope", F.when(own, macro.temperature).otherwise(micro.temperature).alias("temperature"), F.when(own, macro.max_tokens).otherwise(micro.max_tokens).alias("max_tokens"))


@query("response_cache", "SELECT conv_id, turn, sha256('0.7|500|' || text) AS key FROM conversations WHERE role = 'user'")
def response_cache(spark, d):
    u = C.table(spark, d, "conversations").where("role = 'user'")
    return u.select("conv_id", "turn", F.sha2(F.concat(F.lit("0.7|500|"), F.col("text")), 256).alias("key"))


def answer_batch(prompts: DataFrame, store: DataFrame, config: Q.Config) -> tuple[DataFrame, DataFrame]:
    """prompts (id, prompt) with key and reply, and the new cache rows: distinct prompts once, those in the store not at all."""
    head = F.lit(f"{config.temperature}|{config.max_tokens}|")
    keyed = prompts.withColumn("key", F.sha2(F.concat(head, "prompt"), 256))
    misses = keyed.select("key", "prompt").dropDuplicates(["key"]).join(store.select("key"), "key", "left_anti")
    tokens = config.max_tokens

    def run(batches):
        import pandas as pd

        client = Q.TemplateResponder()
        for pdf in batches:
            replies = [client.generate(p, Q.Config(0.7, tokens)).text for p in pdf["prompt"]]
            yield pd.DataFrame({"key": pdf["key"], "reply": replies})

    new = misses.mapInPandas(run, "key string, reply string")
    every = store.select("key", "reply").unionByName(new)
    return keyed.join(every, "key", "left").drop("prompt"), new


@query("batch_cache", "SELECT count(*) AS asked, count(DISTINCT text) AS called, round(1 - count(DISTINCT text) / count(*), 6) AS hit_rate FROM conversations WHERE role = 'user'")
def batch_cache(spark, d):
    u = C.table(spark, d, "conversations").where("role = 'user'").select("conv_id", F.col("text").alias("prompt"))
    got, _ = answer_batch(u, spark.createDataFrame([], "key string, reply string"), Q.Config.macro())
    n = got.where("reply is not null").agg(F.count(F.lit(1)).alias("asked"), F.count_distinct("key").alias("called"))
    return n.withColumn("hit_rate", F.round(1 - F.col("called") / F.col("asked"), 6))


# Template replies over labelled windows, corrupted by id, to measure the checks themselves.
_REPLIES = f"""{L}, rp AS (SELECT event_id, label, place, n,
  CASE event_id % 5 WHEN 1 THEN 'number' WHEN 2 THEN 'place' WHEN 3 THEN 'tone' WHEN 4 THEN 'apology' ELSE 'none' END AS corruption,
  concat_ws(' ', 'At', CASE WHEN event_id % 5 = 2 THEN 'NATION_999' ELSE place END, 'there were', CAST(n + CASE WHEN event_id % 5 = 1 THEN 7 ELSE 0 END AS VARCHAR), 'samples, profile', lower(label),
    CASE WHEN event_id % 5 = 3 THEN CASE WHEN label = 'Calm' THEN 'and dangerous' ELSE 'and harmless' END END, CASE WHEN event_id % 5 = 4 THEN 'I am sorry' END) AS reply FROM lw)"""


def replies(spark, d) -> DataFrame:
    m = F.pmod("event_id", F.lit(5))
    kind = F.when(m == 1, "number").when(m == 2, "place").when(m == 3, "tone").when(m == 4, "apology").otherwise("none")
    text = F.concat_ws(" ", F.lit("At"), F.when(m == 2, "NATION_999").otherwise(F.col("place")), F.lit("there were"), (F.col("n") + F.when(m == 1, 7).otherwise(0)).cast("string"), F.lit("samples, profile"), F.lower("label"), F.when(m == 3, F.when(F.col("label") == "Calm", "and dangerous").otherwise("and harmless")), F.when(m == 4, "I am sorry"))
    return labelled_windows(spark, d).select("event_id", "label", "place", "n", kind.alias("corruption"), text.alias("reply"))


def checked(r: DataFrame, directory: DataFrame) -> DataFrame:
    """Replies with mismatches per check, score and decision, as columns; the directory is one broadcast row."""
    one = directory.agg(F.collect_list("name").alias("_names"))
    said = Q.words(F.col("reply"))
    mentioned = F.array_distinct(F.regexp_extract_all("reply", F.lit("NATION_[0-9]+"), F.lit(0)))
    numbers = F.regexp_extract_all(F.regexp_replace("reply", "NATION_[0-9]+", " "), F.lit(r"[0-9]+(?:\.[0-9]+)?"), F.lit(0))
    wrong = F.when(F.col("label") == "Calm", F.array(*map(F.lit, Q.ALARM))).when(F.col("label").isin(*A.SEVERE), F.array(*map(F.lit, Q.SOOTHING))).otherwise(F.array().cast("array<string>"))
    c = r.crossJoin(F.broadcast(one)).select(
        *r.columns,
        F.size(F.array_except(numbers, F.array(F.col("n").cast("string")))).alias("bad_numbers"),
        F.size(F.array_except(mentioned, F.col("_names"))).alias("bad_places"),
        F.size(F.array_intersect(F.array_distinct(said), wrong)).alias("bad_tone"),
        F.regexp_count("reply", F.lit(Q.GENERIC)).alias("generic"),
    )
    s = F.greatest(F.lit(0), 100 - 20 * (F.col("bad_numbers") + F.col("bad_places") + F.col("bad_tone") + F.col("generic")))
    return c.withColumn("score", s).withColumn("decision", F.when(F.col("score") >= 80, "present").when(F.col("score") < 60, "flag").otherwise("caution"))


_CHECKED = _REPLIES + """, ck AS (SELECT *,
  len(list_filter(list_distinct(regexp_extract_all(regexp_replace(reply, 'NATION_[0-9]+', ' ', 'g'), '[0-9]+')), lambda x: x <> CAST(n AS VARCHAR))) AS bad_numbers,
  len(list_filter(list_distinct(regexp_extract_all(reply, 'NATION_[0-9]+')), lambda x: NOT list_contains(names, x))) AS bad_places,
  CASE WHEN label = 'Calm' AND reply LIKE '%dangerous%' OR label IN ('Aggressive', 'Very Aggressive') AND reply LIKE '%harmless%' THEN 1 ELSE 0 END AS bad_tone,
  CASE WHEN reply LIKE '%I am sorry%' THEN 1 ELSE 0 END AS generic FROM rp, (SELECT list(name) AS names FROM lm) nm),
sc AS (SELECT *, greatest(0, 100 - 20 * (bad_numbers + bad_places + bad_tone + generic)) AS score FROM ck)"""


def _check_query(name: str, column: str):
    @query(name, f"{_CHECKED} SELECT event_id, CAST({column} AS INTEGER) AS {column} FROM sc")
    def run(spark, d):
        return checked(replies(spark, d), C.landmarks(spark, d)).select("event_id", F.col(column).cast("int").alias(column))

    return run


for _name, _column in (("check_numbers", "bad_numbers"), ("check_places", "bad_places"), ("check_tone", "bad_tone"), ("check_generic", "generic"), ("reliability_score", "score")):
    _check_query(_name, _column)


@query("confidence_gate", f"{_CHECKED} SELECT CASE WHEN score >= 80 THEN 'present' WHEN score < 60 THEN 'flag' ELSE 'caution' END AS decision, count(*) AS replies FROM sc GROUP BY 1")
def confidence_gate(spark, d):
    return checked(replies(spark, d), C.landmarks(spark, d)).groupBy("decision").agg(F.count(F.lit(1)).alias("replies"))


@query("score_table", "SELECT CAST(i AS INTEGER) AS issues, CAST(greatest(0, 100 - 20 * i) AS INTEGER) AS score FROM (SELECT unnest(range(7)) AS i)")
def score_table(spark, d):
    return spark.range(7).select(F.col("id").cast("int").alias("issues"), F.greatest(F.lit(0), 100 - 20 * F.col("id")).cast("int").alias("score"))


@query("validator_quality", f"{_CHECKED} SELECT corruption, count(*) AS replies, CAST(sum((bad_numbers > 0)::INT) AS BIGINT) AS by_numbers, CAST(sum((bad_places > 0)::INT) AS BIGINT) AS by_places, CAST(sum((bad_tone > 0)::INT) AS BIGINT) AS by_tone, CAST(sum((generic > 0)::INT) AS BIGINT) AS by_generic FROM sc GROUP BY 1")
def validator_quality(spark, d):
    c = checked(replies(spark, d), C.landmarks(spark, d))
    return c.groupBy("corruption").agg(F.count(F.lit(1)).alias("replies"), F.count_if(F.col("bad_numbers") > 0).alias("by_numbers"), F.count_if(F.col("bad_places") > 0).alias("by_places"), F.count_if(F.col("bad_tone") > 0).alias("by_tone"), F.count_if(F.col("generic") > 0).alias("by_generic"))


@query("groundedness", f"{_CHECKED} SELECT round(avg(CASE WHEN bad_numbers = 0 THEN 1e0 ELSE 0e0 END), 6) AS numbers_ok, round(avg(CASE WHEN bad_places = 0 THEN 1e0 ELSE 0e0 END), 6) AS places_ok, round(avg(CASE WHEN bad_tone = 0 THEN 1e0 ELSE 0e0 END), 6) AS tone_ok, round(avg(score), 6) AS mean_score FROM sc")
def groundedness(spark, d):
    c = checked(replies(spark, d), C.landmarks(spark, d))
    ok = lambda x: F.round(F.avg((F.col(x) == 0).cast("double")), 6)
    return c.agg(ok("bad_numbers").alias("numbers_ok"), ok("bad_places").alias("places_ok"), ok("bad_tone").alias("tone_ok"), F.round(F.avg("score"), 6).alias("mean_score"))


@query("retry_loop")
def retry_loop(spark, d):
    """A responder that makes a number up until the prompt is strict: one retry mends it."""

    class Careless(Q.TemplateResponder):
        def generate(self, text, config):
            r = super().generate(text, config)
            if "Mention no other" in text:
                return r
            return Q.Reply("I am sorry, about 12345 or 777 at NATION_999. " + r.text, r.tokens_in, r.tokens_out, r.seconds)

    return _frame(spark, [ask(spark, d, "How many moderate events were there?", Careless(), retries=n) for n in (0, 1)])


@query("recluster_per_query")
def recluster_per_query(spark, d):
    """The same question with profiles fitted at query time: equal answer, more work."""
    return _frame(spark, [ask(spark, d, "How many moderate events were there?", recluster=r) for r in (False, True)])
