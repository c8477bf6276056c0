"""Quotation linking: reply-ordered conversations without quotes [native].

Lines that start with '>' are quoted; the number of '>' (spaces between them
allowed) is the level. Consecutive lines of one level are one passage. A
passage is normalised (markers off, A-Z lower-cased, white space squeezed) and
hashed, then joined within its conversation to the messages that said it: the
whole unquoted text of an earlier message, one of its own passages, or any of
its consecutive unquoted lines (blank ones left out).
A message answers the latest earlier message that its shallowest passage
is from, else the turn before it. Ordered by reply path, quotes cut out:
a message's answers follow it by turn, each with all that answers it in turn.

Work stays inside one conversation, so the join key is (conv_id, hash) and the
rows of a conversation are never gathered beyond their own text.

Defined cases: null text is empty; attribution lines stay text; quotes that
match no earlier message are cut too but link nothing; ties of turn go to the
larger hash-ordered row id; null conv_id or turn rows form their own group.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

_MARK = r"^[\x20\x09]*((?:>[\x20\x09]?)+)"


def quote_level(line: Column) -> Column:
    return F.length(F.regexp_replace(F.regexp_extract(line, _MARK, 1), "[^>]", ""))


def normalised(text: Column) -> Column:
    squeezed = F.regexp_replace(common.ascii_lower(text), f"[{common.BLANK}]+", " ")
    return F.trim(squeezed)


def with_levels(messages: DataFrame) -> DataFrame:
    """message plus lines: array of struct<level, body>, the markers taken off."""
    cut = F.split(F.regexp_replace(F.coalesce("text", F.lit("")), "\r", ""), "\n", -1)
    return messages.withColumn("lines", F.transform(cut, lambda x: F.struct(quote_level(x).alias("level"), F.regexp_replace(x, _MARK, "").alias("body"))))


def passages(lines: Column) -> Column:
    """Runs of equal level as array of struct<level, body>."""
    empty = F.array().cast("array<struct<level:int,body:string>>")

    def step(acc: Column, x: Column) -> Column:
        last = F.element_at(acc, -1)
        grown = F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(x["level"].alias("level"), F.concat_ws("\n", last["body"], x["body"]).alias("body"))))
        return F.when((F.size(acc) > 0) & (F.get(acc, F.size(acc) - 1)["level"] == x["level"]), grown).otherwise(F.concat(acc, F.array(F.struct(x["level"].alias("level"), x["body"].alias("body")))))

    return F.aggregate(lines, empty, step)


def _spans(lines: Column, sizes: Column) -> Column:
    """Texts of as many consecutive lines as each of sizes says."""
    at = lambda n: F.when(F.size(lines) >= n, F.sequence(F.lit(1), F.size(lines) - n + 1)).otherwise(F.array().cast("array<int>"))
    return F.flatten(F.transform(sizes, lambda n: F.transform(at(n), lambda i: F.array_join(F.slice(lines, i, n), " "))))


def link_replies(messages: DataFrame) -> DataFrame:
    """conv_id, turn, role, own_text, n_quotes, reply_to: the answered turn, by quote or else the turn before; quoted_row: the quoted message of that turn."""
    has = F.exists("lines", lambda x: x["level"] > 0)
    read = with_levels(messages.select("conv_id", "turn", "role", "text")).withColumn("row", F.xxhash64("role", "text"))
    runs = read.withColumn("runs", F.when(has, passages(F.col("lines"))).otherwise(F.array(F.struct(F.lit(0).alias("level"), F.coalesce("text", F.lit("")).alias("body")))))
    own = F.trim(F.array_join(F.transform(F.filter("runs", lambda x: x["level"] == 0), lambda x: F.trim(x["body"])), "\n"), F.lit("\n"))
    base = runs.withColumns({"own_text": own, "quotes": F.filter("runs", lambda x: (x["level"] > 0) & (normalised(x["body"]) != ""))})
    own_lines = F.filter(F.transform(F.filter("lines", lambda x: x["level"] == 0), lambda x: normalised(x["body"])), lambda x: x != "")
    said_parts = F.array_distinct(F.filter(F.concat(
        F.array(normalised(F.col("own_text"))),
        F.transform(F.filter("runs", lambda x: x["level"] == 0), lambda x: normalised(x["body"])),
        _spans(F.col("own_lines"), F.col("sizes")),
    ), lambda x: x != ""))
    n_lines = F.size(F.filter(F.split(F.col("q.body"), "\n", -1), lambda x: normalised(x) != ""))
    quoted = base.where(F.size("quotes") > 0).select(
        "conv_id", "turn", "row",
        F.explode("quotes").alias("q")).select("conv_id", "turn", "row", F.col("q.level").alias("level"), n_lines.alias("n_lines"), F.xxhash64(normalised(F.col("q.body"))).alias("hash"))
    # Only conversations that quote at all need an index of what was said in them, in spans as long as what they quote.
    asked = quoted.groupBy("conv_id").agg(F.collect_set("n_lines").alias("sizes"))
    said = base.join(asked, "conv_id").withColumn("own_lines", own_lines).select("conv_id", F.col("turn").alias("said_turn"), F.col("row").alias("said_row"), F.explode(said_parts).alias("part")).select("conv_id", "said_turn", "said_row", F.xxhash64("part").alias("hash")).distinct()
    links = quoted.join(said, ["conv_id", "hash"]).where(F.col("said_turn") < F.col("turn"))
    best = links.groupBy("conv_id", "turn", "row").agg(F.max(F.struct((-F.col("level")).alias("neg"), "said_turn", "said_row")).alias("b"))
    best = best.select("conv_id", "turn", "row", F.col("b.said_turn").alias("quoted_turn"), F.col("b.said_row").alias("quoted_row"))
    joined = base.join(best, ["conv_id", "turn", "row"], "left")
    before = F.lag("turn").over(Window.partitionBy("conv_id").orderBy("turn", "row"))
    return joined.select("conv_id", "turn", "role", "row", "own_text", F.size("quotes").cast("long").alias("n_quotes"), F.coalesce("quoted_turn", before).alias("reply_to"), F.col("quoted_turn").isNotNull().alias("linked"), "quoted_row")


def by_reply_path(m: Column) -> Column:
    """Messages, given by turn, in the order of a walk through the tree of replies.

    Messages that each answer the one before are a run, kept whole. A run that starts
    elsewhere comes after the run that it answers into, those into later messages first.
    """
    answered = lambda x: F.array_max(F.transform(m, lambda y, j: F.when(y["turn"].eqNullSafe(x["reply_to"]) & (y["row"] == x["quoted_row"]), j)))
    at = F.transform(m, lambda x, i: F.struct(i.alias("at"), F.when(x["quoted_row"].isNotNull(), answered(x)).otherwise(i - 1).alias("to")))
    starts = F.filter(at, lambda x: (x["at"] > 0) & (x["to"] != x["at"] - 1))
    first = F.array(F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("path")))
    path = lambda runs, i: F.element_at(F.filter(runs, lambda r: r["at"] <= i), -1)["path"]
    runs = F.aggregate(starts, first, lambda acc, x: F.concat(acc, F.array(F.struct(x["at"].alias("at"), F.concat(path(acc, x["to"]), F.array(-x["to"], x["at"])).alias("path")))))
    keyed = lambda r: F.array_sort(F.transform(m, lambda x, i: F.struct(path(r, i).alias("path"), i.alias("at"), x.alias("m"))))
    walked = F.transform(F.element_at(F.transform(F.array(runs), keyed), 1), lambda x: x["m"])  # runs are made once
    return F.when(F.exists(m, lambda x: x["quoted_row"].isNotNull()), walked).otherwise(m)


def conversations(messages: DataFrame) -> DataFrame:
    """One row per conversation: turns by reply path, as array of struct<turn, reply_to, role, text>, quotes cut out."""
    linked = link_replies(messages)
    item = F.struct("turn", "row", "reply_to", "quoted_row", "role", F.col("own_text").alias("text"))
    got = linked.groupBy("conv_id").agg(F.array_sort(F.collect_list(item)).alias("m"), F.sum("n_quotes").alias("n_quotes"), F.sum(F.col("linked").cast("long")).alias("n_linked"))
    got = got.withColumn("m", by_reply_path(F.col("m")))
    return got.select("conv_id", F.size("m").cast("long").alias("n_messages"), "n_quotes", "n_linked", F.transform("m", lambda x: F.struct(x["turn"].alias("turn"), x["reply_to"].alias("reply_to"), x["role"].alias("role"), x["text"].alias("text"))).alias("messages"))


def op7_chat_quotes(spark, sf_dir: str) -> DataFrame:
    got = conversations(common.table(spark, sf_dir, "conversations"))
    body = F.array_join(F.transform("messages", lambda x: F.concat_ws("|", x["turn"].cast("string"), F.coalesce(x["reply_to"].cast("string"), F.lit("-")), F.coalesce(x["role"], F.lit("")), x["text"])), "\n\n")
    return got.select("conv_id", "n_messages", "n_quotes", "n_linked", F.sha2(body, 256).alias("messages_sha256"))


OP7_SQL = """
WITH m AS (
  SELECT conv_id, turn, role, trim(coalesce(text, ''), chr(10) || ' ') AS text,
         lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS reply_to FROM conversations
)
SELECT conv_id, count(*) AS n_messages, CAST(0 AS BIGINT) AS n_quotes, CAST(0 AS BIGINT) AS n_linked,
       sha256(string_agg(concat_ws('|', CAST(turn AS VARCHAR), coalesce(CAST(reply_to AS VARCHAR), '-'), coalesce(role, ''), text), chr(10) || chr(10) ORDER BY turn)) AS messages_sha256
FROM m GROUP BY conv_id
"""
