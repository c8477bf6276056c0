"""Queries of intents, scopes, times and places."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import questions as Q
from ..sources import carriers as C
from .registry import query

_QS = "qs AS (SELECT * FROM (VALUES " + ", ".join(f"({i}, '{t}', '{e}')" for i, t, e in Q.QUESTIONS) + ") t(qid, text, expected))"

_CORPUS = [("articles", ["the", "a", "an"]), ("german", ["der", "die", "das", "und"]), ("french", ["le", "la", "les", "et"])]
#: A lexicon of the given texts: intent, category, scope, priority, terms, and the lang for which the intent is expected.
_TEXTS = [(n, c, s, i, t, x) for i, ((n, t), (c, s, x)) in enumerate(zip(_CORPUS, (("Germanic", "macro", "en"), ("Germanic", "micro", "de"), ("Romance", "macro", "fr")), strict=True))]
_CLASS = (
    "lex AS (SELECT * FROM (VALUES " + ", ".join(f"('{n}', '{c}', '{s}', {i}, {t}, '{x}')" for n, c, s, i, t, x in _TEXTS) + ") t(intent, category, scope, priority, terms, lang)), "
    "qs AS (SELECT doc_id, list_distinct(string_split_regex(lower(coalesce(text, '')), '[^a-z]+')) AS w, coalesce(x.intent, 'unknown') AS expected FROM documents LEFT JOIN lex x USING (lang)), "
    "sc AS (SELECT doc_id, expected, intent, category, scope, priority, len(list_intersect(w, terms)) AS score FROM qs CROSS JOIN lex), "
    "cl AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, priority) AS n FROM sc) WHERE n = 1)"
)
W = f"WITH {_CLASS}"


def classified_texts(spark, d):
    """doc_id, expected, intent, category, scope and score of every document."""
    lex = spark.createDataFrame([r[:5] for r in _TEXTS], "intent string, category string, scope string, priority int, terms array<string>")
    expected = F.lit("unknown")
    for n, *_, x in _TEXTS:
        expected = F.when(F.col("lang") == x, n).otherwise(expected)
    return Q.classify(C.table(spark, d, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"), expected.alias("expected")), lex).drop("text")


@query("intent_classify", f"{W} SELECT doc_id, CASE WHEN score > 0 THEN intent ELSE 'unknown' END AS intent, CAST(score AS INTEGER) AS score, expected = CASE WHEN score > 0 THEN intent ELSE 'unknown' END AS as_expected FROM cl")
def intent_classify(spark, d):
    """The intent of every document's text, and whether its lang expects it."""
    return classified_texts(spark, d).select("doc_id", "intent", "score", (F.col("intent") == F.col("expected")).alias("as_expected"))


@query("intent_unknown", f"{W} SELECT doc_id, 'try: articles, french, german' AS hint FROM cl WHERE score = 0")
def intent_unknown(spark, d):
    hint = "try: " + ", ".join(sorted(x[0] for x in _TEXTS))
    return classified_texts(spark, d).where("intent = 'unknown'").select("doc_id", F.lit(hint).alias("hint"))


@query("intent_scope", f"{W} SELECT doc_id, scope FROM cl WHERE score > 0")
def intent_scope(spark, d):
    return classified_texts(spark, d).where("scope is not null").select("doc_id", "scope")


@query("intent_category", f"{W} SELECT category, count(*) AS questions FROM cl WHERE score > 0 GROUP BY 1")
def intent_category(spark, d):
    return classified_texts(spark, d).where("category is not null").groupBy("category").agg(F.count(F.lit(1)).alias("questions"))


@query("lexicon_proposal", "SELECT w AS term, count(DISTINCT doc_id) AS documents FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS w FROM documents WHERE lang = 'en') WHERE length(w) >= 5 GROUP BY 1 ORDER BY documents DESC, term LIMIT 20")
def lexicon_proposal(spark, d):
    """Candidate terms of a domain: its most widespread longer words; a model would be asked in their place."""
    docs = C.table(spark, d, "documents").where("lang = 'en'")
    w = docs.select("doc_id", F.explode(F.array_distinct(Q.words(F.col("text")))).alias("term")).where(F.length("term") >= 5)
    return w.groupBy("term").agg(F.count_distinct("doc_id").alias("documents")).orderBy(F.desc("documents"), "term").limit(20)


@query("time_window_extract", f"WITH {_QS}, b AS (SELECT qid, string_split_regex(lower(text), '[^a-z]+') AS w FROM qs) SELECT qid, CASE WHEN list_contains(w, 'night') THEN 0 WHEN list_contains(w, 'morning') THEN 6 WHEN list_contains(w, 'afternoon') THEN 12 WHEN list_contains(w, 'evening') THEN 17 END AS from_hour, CASE WHEN list_contains(w, 'night') THEN 5 WHEN list_contains(w, 'morning') THEN 11 WHEN list_contains(w, 'afternoon') THEN 16 WHEN list_contains(w, 'evening') THEN 22 END AS to_hour FROM b")
def time_window_extract(spark, d):
    q = Q.questions(spark).withColumn("h", Q.hours_of(F.col("text")))
    return q.select("qid", F.col("h.from").alias("from_hour"), F.col("h.to").alias("to_hour"))


@query("place_extract", f"WITH {_QS} SELECT qid, max(n_name) AS place FROM qs LEFT JOIN nation ON list_contains(string_split_regex(text, '[^A-Za-z0-9_]+'), n_name) GROUP BY qid")
def place_extract(spark, d):
    return Q.place_of(Q.questions(spark), C.landmarks(spark, d)).select("qid", "place")


@query("volume_questions", "WITH lx AS (SELECT * FROM (VALUES " + ", ".join(f"('{n}', {i}, {t})" for i, (n, t) in enumerate(_CORPUS)) + ") t(intent, priority, terms)), q AS (SELECT conv_id, turn, list_distinct(string_split_regex(lower(text), '[^a-z]+')) AS w FROM conversations WHERE role = 'user'), s AS (SELECT conv_id, turn, intent, len(list_intersect(w, terms)) AS score, row_number() OVER (PARTITION BY conv_id, turn ORDER BY len(list_intersect(w, terms)) DESC, priority) AS n FROM q CROSS JOIN lx) SELECT CASE WHEN score > 0 THEN intent ELSE 'unknown' END AS intent, count(*) AS questions FROM s WHERE n = 1 GROUP BY 1")
def volume_questions(spark, d):
    """Intent classification over all user turns."""
    lex = spark.createDataFrame([(n, "", "", i, t) for i, (n, t) in enumerate(_CORPUS)], "intent string, category string, scope string, priority int, terms array<string>")
    u = C.table(spark, d, "conversations").where("role = 'user'").select("conv_id", "turn", "text")
    return Q.classify(u, lex).groupBy("intent").agg(F.count(F.lit(1)).alias("questions"))
