"""Questions: intents, scopes, times, places; facts, prompts, replies, checks; usage meters."""

from __future__ import annotations

import hashlib
import math
import re
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Our own lexicon: intent, category, scope, priority, terms.
LEXICON = [
    ("hotspots", "Geospatial", "macro", 1, ["aggressive", "harsh", "dangerous", "unsafe", "hotspot", "hotspots"]),
    ("dwell", "Operational", "macro", 2, ["dwell", "idle", "wait", "waiting", "stay", "stops", "longest"]),
    ("count", "Event Counting", "macro", 3, ["count", "many", "number", "total", "moderate"]),
    ("efficiency", "Temporal", "macro", 4, ["morning", "evening", "efficiency", "efficient", "compare", "route", "routes"]),
    ("spatial", "Geospatial", "macro", 5, ["around", "near", "pattern", "patterns", "nation", "area"]),
    ("event", "Behavioral", "micro", 6, ["event", "braking", "turn", "shock", "explain", "why"]),
]
#: Our own questions: id, text, expected intent.
QUESTIONS = [
    (1, "Where does aggressive driving happen?", "hotspots"),
    (2, "Show the most dangerous places and harsh manoeuvres", "hotspots"),
    (3, "Which zone has the longest dwell?", "dwell"),
    (4, "Where do buses wait or idle?", "dwell"),
    (5, "How many moderate events were there?", "count"),
    (6, "Give the total number of calm windows", "count"),
    (7, "Compare morning and evening efficiency", "efficiency"),
    (8, "Are routes more efficient in the evening?", "efficiency"),
    (9, "What patterns are there around NATION_3?", "spatial"),
    (10, "Describe the area near NATION_12", "spatial"),
    (11, "Explain this event: why the sudden braking?", "event"),
    (12, "What is the weather tomorrow?", "unknown"),
]
#: Hours of named bands, first and last inclusive.
BANDS = {"night": (0, 5), "morning": (6, 11), "afternoon": (12, 16), "evening": (17, 22)}
ALARM = ["dangerous", "severe", "alarming", "reckless"]
SOOTHING = ["gentle", "smooth", "harmless", "relaxed"]
GENERIC = r"(?i)(i am sorry|i apologi[sz]e|as an ai|i cannot|unable to answer)"
JARGON = r"(?i)(chunk|sampled|dataset|in the data provided)"


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")


def lexicon(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(LEXICON, "intent string, category string, scope string, priority int, terms array<string>")


def questions(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(QUESTIONS, "qid int, text string, expected string")


def classify(df: DataFrame, lex: DataFrame, key: str = "qid") -> DataFrame:
    """df with intent, category, scope and score: most terms matched, then priority; "unknown" without any. The lexicon is one broadcast row."""
    one = lex.agg(F.collect_list(F.struct("intent", "category", "scope", "priority", "terms")).alias("_lex"))
    w = df.withColumn("_w", F.array_distinct(words(F.col("text")))).crossJoin(F.broadcast(one))
    scored = F.transform("_lex", lambda e: F.struct((-F.size(F.array_intersect(F.col("_w"), e["terms"]))).alias("neg"), e["priority"].alias("priority"), e["intent"].alias("intent"), e["category"].alias("category"), e["scope"].alias("scope")))
    b = w.withColumn("_b", F.array_min(scored))
    hit = F.col("_b.neg") < 0
    return b.select(*df.columns, F.when(hit, F.col("_b.intent")).otherwise("unknown").alias("intent"), F.when(hit, F.col("_b.category")).alias("category"), F.when(hit, F.col("_b.scope")).alias("scope"), (-F.col("_b.neg")).cast("int").alias("score"))


PROFILES = ["Calm", "Moderate", "Slightly Unstable", "Aggressive", "Very Aggressive"]


def label_of(text: Column) -> Column:
    """The driving profile a question names, the longest name first, or null."""
    out = F.lit(None).cast("string")
    for name in sorted(PROFILES, key=len):
        out = F.when(F.lower(text).rlike(rf"\b{name.lower()}\b"), F.lit(name)).otherwise(out)
    return out


def event_of(text: Column) -> Column:
    """The number of the event a question names, or null."""
    return F.nullif(F.regexp_extract(text, r"(?i)\bevent\s+#?([0-9]+)", 1), F.lit("")).try_cast("long")


def hours_of(text: Column) -> Column:
    """The hour band a question names, as struct<from, to>, or null."""
    out = F.lit(None).cast("struct<from:int,to:int>")
    for name, (a, b) in reversed(BANDS.items()):
        out = F.when(F.array_contains(words(text), name), F.struct(F.lit(a).alias("from"), F.lit(b).alias("to"))).otherwise(out)
    return out


def place_of(df: DataFrame, places: DataFrame) -> DataFrame:
    """df with the longest landmark name its text mentions. The directory is one broadcast row."""
    one = places.agg(F.collect_list("name").alias("_names"))
    found = F.filter("_names", lambda n: F.array_contains(F.split(F.col("text"), "[^A-Za-z0-9_]+"), n))
    longest = F.array_max(F.transform(found, lambda n: F.struct(F.length(n).alias("l"), n.alias("n"))))["n"]
    return df.crossJoin(F.broadcast(one)).withColumn("place", longest).drop("_names")


@dataclass(frozen=True)
class Config:
    """Generation settings of a kind of task."""

    temperature: float
    max_tokens: int

    @classmethod
    def macro(cls) -> Config:
        return cls(0.7, 500)

    @classmethod
    def micro(cls) -> Config:
        return cls(0.5, 150)


@dataclass(frozen=True)
class Reply:
    text: str
    tokens_in: int
    tokens_out: int
    seconds: float


@dataclass(frozen=True)
class Facts:
    """What a reply may say: a title, numbers, places, the profile spoken of."""

    title: str
    numbers: dict[str, float]
    places: list[tuple[str, float]]
    label: str | None = None


def tokens(text: str) -> int:
    """Four characters to a token where no count comes with a reply."""
    return math.ceil(len(text) / 4)


def fact_block(facts: Facts) -> str:
    """The compact context: a title, totals, then ranked places."""
    lines = [facts.title, *[f"- {k}: {_number(v)}" for k, v in facts.numbers.items()]]
    lines += [f"{i}. {name} ({_number(n)})" for i, (name, n) in enumerate(facts.places, 1)]
    return "\n".join(lines)


def _number(v: float) -> str:
    return str(int(v)) if float(v).is_integer() else f"{v:.2f}"


INSTRUCTIONS = {
    "hotspots": "Name the places in order and say how often it happened there.",
    "dwell": "Say where vehicles stay longest, in minutes.",
    "count": "State the count plainly.",
    "efficiency": "Compare the two periods in one or two sentences.",
    "spatial": "Describe what happens around the place.",
    "event": "Explain the single event from its surroundings.",
}
REPRESENTATION = {"hotspots": "geographic anchors", "dwell": "summary", "count": "count", "efficiency": "summary", "spatial": "geographic anchors", "event": "geographic anchors"}


def prompt(intent: str, block: str, question: str, strict: bool = False) -> str:
    rule = "Use only the facts below; repeat their numbers exactly." + (" Mention no other number or place." if strict else "")
    return f"{INSTRUCTIONS.get(intent, 'Answer briefly.')} {rule}\n\n{block}\n\nQuestion: {question}"


@dataclass
class TemplateResponder:
    """A deterministic writer that says the facts of a prompt; stands in for a model. Its latency is simulated, never measured."""

    fixed_seconds: float = 0.2
    seconds_per_token: float = 0.002
    calls: int = 0

    def generate(self, text: str, config: Config) -> Reply:
        self.calls += 1
        body = text.split("\n\n")[1] if "\n\n" in text else text
        answer = "The facts show: " + "; ".join(x.strip("- ") for x in body.split("\n")) + "."
        answer = answer[: config.max_tokens * 4]
        used = tokens(text), tokens(answer)
        return Reply(answer, *used, self.fixed_seconds + self.seconds_per_token * sum(used))


@dataclass
class Cache:
    """Replies by a hash of prompt and settings."""

    held: dict[str, Reply] = field(default_factory=dict)
    hits: int = 0
    asked: int = 0

    @staticmethod
    def key(text: str, config: Config) -> str:
        return hashlib.sha256(f"{config.temperature}|{config.max_tokens}|{text}".encode()).hexdigest()

    def get_or_call(self, text: str, config: Config, call: Callable[[str, Config], Reply]) -> Reply:
        self.asked += 1
        key = self.key(text, config)
        if key in self.held:
            self.hits += 1
        else:
            self.held[key] = call(text, config)
        return self.held[key]


def numbers_in(text: str) -> list[str]:
    return re.findall(r"[0-9]+(?:\.[0-9]+)?", re.sub(r"(?<=[0-9]),(?=[0-9]{3})", "", text))


def issues(reply: str, facts: Facts, directory: list[str]) -> dict[str, int]:
    """Mismatches by check: numbers, places, tone, generic wording."""
    known = {n for n, _ in facts.places}
    bare = reply
    for name in sorted(directory, key=len, reverse=True):
        bare = bare.replace(name, " ")
    values = [*facts.numbers.values(), *[n for _, n in facts.places], *range(1, len(facts.places) + 1)]
    bad_numbers = sum(not any(f"{v:.{len(x.partition('.')[2])}f}" == x for v in values) for x in numbers_in(re.sub(r"NATION_[0-9]+", " ", bare)))
    bad_places = sum(p not in known and p not in directory for p in set(re.findall(r"NATION_[0-9]+", reply)))
    said = set(re.findall("[a-z]+", reply.lower()))
    wrong = ALARM if facts.label == "Calm" else SOOTHING if facts.label in ("Aggressive", "Very Aggressive") else []
    return {"numbers": bad_numbers, "places": bad_places, "tone": len(said & set(wrong)), "generic": len(re.findall(GENERIC, reply))}


def score(count: int) -> int:
    return max(0, 100 - 20 * count)


def gate(s: int) -> str:
    return "present" if s >= 80 else "flag" if s < 60 else "caution"


def cost(tokens_in: float, tokens_out: float, price_in: float = 0.05, price_out: float = 0.08) -> float:
    """USD of a call at prices per million tokens."""
    return tokens_in * price_in / 1e6 + tokens_out * price_out / 1e6


@dataclass
class Answer:
    question: str
    intent: str
    text: str
    score: int
    decision: str
    tokens_in: int
    tokens_out: int
    calls: int
    model_seconds: float
    spark_seconds: float


def answer(question: str, intent: str, facts: Facts, directory: list[str], responder: TemplateResponder, cache: Cache | None = None, retries: int = 1, began: float | None = None) -> Answer:
    """One call, checks, score; a flagged reply is asked for again with a stricter prompt."""
    config = Config.micro() if intent == "event" else Config.macro()
    spent = [0, 0, 0.0]
    spark_seconds = time.perf_counter() - began if began else 0.0
    for attempt in range(retries + 1):
        text = prompt(intent, fact_block(facts), question, strict=attempt > 0)
        reply = cache.get_or_call(text, config, responder.generate) if cache else responder.generate(text, config)
        spent = [spent[0] + reply.tokens_in, spent[1] + reply.tokens_out, spent[2] + reply.seconds]
        s = score(sum(issues(reply.text, facts, directory).values()))
        if gate(s) != "flag":
            break
    return Answer(question, intent, reply.text, s, gate(s), spent[0], spent[1], attempt + 1, spent[2], spark_seconds)
