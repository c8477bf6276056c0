"""Toxicity from class-conditional Kneser-Ney models.

Two bigram models, of toxic and of ordinary texts: a class's discounted bigram
counts are filled up with backoff counts, which its continuation counts (in how
many contexts a word occurs) share out; those are discounted too and filled up with
counts that both classes share alike, so an expression that is rare in either class
says next to nothing. A text's evidence is log P_toxic - log P_ordinary, summed over
its words as far as each exceeds CLEAR (below that it is the noise of rare words, which
long texts gather), and taken per word and per square root of words, so that
length is levelled out; a logistic fit on labelled rows kept apart turns that into a score.

The model is fitted on a bounded sample: the `per_class` labelled rows of
each class with the lowest hashes of doc_id, whole texts; three quarters of them
for counts, the rest for the logistic fit. The bound is on rows of the
labelled sample alone; every document is scored, whole. Counts are taken in Spark; bigrams and words seen
once are left to the backoff, so the table sent to the executors is bounded by half the sample's words.

Defined cases: a null or empty text has no evidence, and its score comes
from the fitted intercept alone; several labels of a doc_id count as
toxic if one of them is; of several texts of a doc_id one, by hash, is learnt from; labels without text don't count; with one class missing, the score is that class's share.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, wordhash

PER_CLASS = 6000
#: The discount, and the counts that the level below shares out between the classes.
DISCOUNT, BACKOFF = 0.75, 12.0
#: Fixed value: what a word must say for toxic, in nats, before it counts as evidence.
CLEAR = 1.0
_PAIR = np.uint64(0xA24BAED4963EE407)
_BITS = 22


def held_out(doc_id: str = "doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(5)) == 0


def _pairs(words: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of (word before, word) and the former; the start of a row counts as a word."""
    before = np.empty_like(words)
    before[1:] = words[:-1]
    first = ends[:-1][np.diff(ends) > 0]
    before[first] = np.uint64(1)
    return wordhash.mix(before * _PAIR + words), before


class Model:
    """Sorted hashes with their log ratios: of words and of bigrams."""

    def __init__(self, words, word_ratio, pairs, pair_ratio, weights):
        self.words, self.pairs = self._table(words, word_ratio), self._table(pairs, pair_ratio)
        self.weights = weights

    @staticmethod
    def _table(keys, values):
        order = np.argsort(keys)
        keys, values = np.asarray(keys, np.uint64)[order], np.asarray(values, np.float64)[order]
        hit = np.zeros(1 << _BITS, bool)
        hit[(keys >> np.uint64(64 - _BITS)).astype(np.int64)] = True
        return keys, values, hit

    @staticmethod
    def _look(table, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of x that the table has, and its values there."""
        keys, values, hit = table
        maybe = np.flatnonzero(hit[(x >> np.uint64(64 - _BITS)).astype(np.int64)])
        at = np.searchsorted(keys, x[maybe])
        ok = at < len(keys)
        ok[ok] = keys[at[ok]] == x[maybe][ok]
        return maybe[ok], values[at[ok]]

    def ratios(self, words: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """log P_toxic(w|v) - log P_ordinary(w|v) for each word."""
        out = np.zeros(len(words))
        for table, x in ((self.words, words), (self.pairs, _pairs(words, ends)[0])):  # a known bigram overrides its word
            at, value = self._look(table, x)
            out[at] = value
        return out

    def features(self, texts: pa.Array) -> np.ndarray:
        words, ends = wordhash.word_hashes(texts, lower=True, punctuation=True)
        n = np.diff(ends)
        total = np.zeros(len(words) + 1)
        np.cumsum(np.maximum(self.ratios(words, ends) - CLEAR, 0), out=total[1:])
        clear = total[ends[1:]] - total[ends[:-1]]
        return np.column_stack([np.ones(len(n)), np.log1p(n) / 10, np.log1p(clear), 20 * clear / np.maximum(n, 1), clear / np.sqrt(np.maximum(n, 1))])

    def score(self, texts: pa.Array) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.features(texts) @ self.weights, -30, 30)))


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bigram counts of a batch: class, hashes of the word before, the word and the pair, count."""
    for batch in (x for whole in batches for x in wordhash.slices(whole)):
        words, ends = wordhash.word_hashes(batch.column("text"), lower=True, punctuation=True)
        if not len(words):
            continue
        pairs, before = _pairs(words, ends)
        toxic = np.repeat(batch.column("toxic").to_numpy(zero_copy_only=False).astype(np.int64), np.diff(ends))
        for c in (0, 1):
            own = np.flatnonzero(toxic == c)
            key, at, n = np.unique(pairs[own], return_index=True, return_counts=True)
            if len(key):
                yield pa.RecordBatch.from_pydict({"toxic": np.full(len(key), c, np.int32), "v": before[own][at].view(np.int64), "w": words[own][at].view(np.int64), "pair": key.view(np.int64), "n": n.astype(np.int64)})


def labelled(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """doc_id, text, toxic of the bounded sample."""
    texts = docs.select("doc_id", "text").where(F.length("text") > 0)
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    known = known.join(texts.select("doc_id"), "doc_id", "left_semi")
    order = [F.xxhash64("doc_id"), F.col("doc_id")]
    sample = known.where("toxic = 1").orderBy(*order).limit(per_class).union(known.where("toxic = 0").orderBy(*order).limit(per_class))
    return texts.join(F.broadcast(sample), "doc_id").groupBy("doc_id").agg(F.min_by("text", F.struct(F.xxhash64("text"), "text")).alias("text"), F.first("toxic").alias("toxic"))


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Model | float:
    """The model, or the share of toxic rows where a class has no rows."""
    spark = docs.sparkSession
    sample = common.stored(spark, labelled(docs, labels, per_class), "labelled")
    sizes = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if sizes.get(0, 0) < 4 or sizes.get(1, 0) < 4:
        return sizes.get(1, 0) / max(1, sum(sizes.values()))
    apart = F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(4)) == 0
    counts = common.stored(spark, sample.where(~apart).select("text", "toxic").mapInArrow(_count, "toxic int, v long, w long, pair long, n long").groupBy("pair", "v", "w").agg(*[F.sum(F.when(F.col("toxic") == c, F.col("n")).otherwise(0)).alias(f"n{c}") for c in (0, 1)]), "bigrams")
    words = counts.groupBy("w").agg(*[F.sum((F.col(f"n{c}") > 0).cast("long")).alias(f"k{c}") for c in (0, 1)]).toArrow()
    pairs = counts.where("n0 + n1 > 1").select("pair", "w", "n0", "n1").toArrow()
    model = _model(*({n: t[n].to_numpy() for n in t.column_names} for t in (words, pairs)))
    fitted = sample.where(apart).select("text", "toxic").toArrow()
    x, y = model.features(fitted["text"]), fitted["toxic"].to_numpy().astype(float)
    model.weights = _logistic(x, y)
    return model


def _ratio(counts: list[np.ndarray], sizes: list[float], toxic_share) -> np.ndarray:
    """log P_toxic - log P_ordinary from discounted counts and BACKOFF counts that the level below shares out.

    sizes: the classes' totals, so that the larger class does not weigh more.
    """
    total = max(sum(sizes), 1)
    top, low = (np.maximum(n - DISCOUNT, 0) / max(2 * s / total, 1e-9) for n, s in zip(counts[::-1], sizes[::-1], strict=True))
    return np.log(top + BACKOFF * toxic_share) - np.log(low + BACKOFF * (1 - toxic_share))


def _model(words: dict, pairs: dict) -> Model:
    """Continuation counts give the words' ratios, which are the level below the bigrams'."""
    base = _ratio([words["k0"], words["k1"]], [float(words["k0"].sum()), float(words["k1"].sum())], 0.5)
    order = np.argsort(words["w"])
    below = base[order[np.searchsorted(words["w"][order], pairs["w"])]]
    ratio = _ratio([pairs["n0"], pairs["n1"]], [float(pairs["n0"].sum()), float(pairs["n1"].sum())], 1 / (1 + np.exp(-below)))
    keep = words["k0"] + words["k1"] > 1
    u = lambda x: x.astype(np.int64).view(np.uint64)
    return Model(u(words["w"][keep]), base[keep], u(pairs["pair"]), ratio, np.zeros(5))


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """Newton steps of a ridge logistic regression with both classes weighing the same."""
    w = np.zeros(x.shape[1])
    mass = np.where(y > 0, len(y) / max(1, 2 * y.sum()), len(y) / max(1, 2 * (1 - y).sum()))
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (mass * p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w)), x.T @ (mass * (y - p)) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-9:
            break
    return w


def score(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> DataFrame:
    """docs with score and predicted, in place of columns of docs of these names; every row and every other column stays."""
    model = fit(docs, labels, per_class)
    own = docs.select(*[c for c in docs.columns if c.lower() not in ("score", "predicted")])
    if not isinstance(model, Model):
        return own.withColumn("score", F.lit(float(model))).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (x for whole in batches for x in wordhash.slices(whole)):
            got = model.score(batch.column("text"))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(got), pa.array((got >= 0.5).astype(np.int32))], names=[*batch.schema.names, "score", "predicted"])

    from pyspark.sql import types as T

    schema = T.StructType([*own.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return own.mapInArrow(run, schema)


def op2_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score(docs, common.table(spark, sf_dir, "labels"))
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", "predicted")
