"""Benchmark decontamination: a BM25 index of test items, searched by every training passage.

Items are indexed as BM25 impacts, divided by the item's score against itself,
so a passage that holds the whole item scores 1. Postings lie in blocks with
their largest impacts. Every document is cut into overlapping passages, longer
than twice the longest item of the benchmark, so that each item lies whole in some passage. A
passage is searched by block-max WAND for all items at or above `threshold`; it
enters the search only if its essential terms, without which no item can reach
the threshold, leave it a chance (the pivot condition, tested over arrays).
Retrieved pairs are verified: shares of the item's word trigrams that the passage
has too, for the question and for the answer (the last sentence, or the last
fifth of the words), must both reach `overlap`.

The index is sent to every task only as blocks of at most `INDEX_ITEMS` items;
a larger benchmark is searched block after block. Its number of items, document
frequencies and lengths are counted over all of it, so blocks change no score.

Defined cases: words are runs of letters and digits with A-Z lower-cased, bytes
beyond ASCII counting as letters; null or empty texts hold nothing; items
without words are never found; items of fewer than three words are matched whole;
rows that repeat a doc_id or an item_id are judged each on its own, and the best overlap of a pair is returned; null ids pair like others.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, wordhash

#: Fixed values of BM25.
K1, B = 1.2, 0.75
INDEX_ITEMS = 5000
INDEX_BYTES = 32 << 20
BLOCK = 64
_WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+")


def words_of(text: str | None) -> list[bytes]:
    return _WORD.findall((text or "").encode().lower())


def answer_start(text: str) -> int:
    """The number of words before the answer: the last sentence, or the last fifth of a text of one sentence."""
    n = len(words_of(text))
    cuts = [len(words_of(text[: m.end()])) for m in re.finditer(r"[.?!:](?=\s)", text)]
    cuts = [c for c in cuts if 0 < c < n]
    return cuts[-1] if cuts else n - max(1, n // 5)


def grams(words: list) -> set:
    return {tuple(words[i : i + 3]) for i in range(len(words) - 2)} if len(words) > 2 else {tuple(words)} if words else set()


class Index:
    """Block-max BM25 index of some items. Impacts are shares of an item's own score.

    whole: of a benchmark that these are only a block of, the number of items, its words, the longest item's words, and the items of each term of the block.
    """

    def __init__(self, items: list[tuple[int, str]], threshold: float, whole: tuple[int, int, int, dict[int, int]] | None = None):
        self.ids, self.texts, self.threshold = [i for i, _ in items], [t or "" for _, t in items], threshold
        array = pa.array(self.texts, pa.string())
        hashes, ends = wordhash.word_hashes(array, lower=True, punctuation=True)
        self.longest = int(np.diff(ends).max(initial=1))
        held = [Counter(hashes[ends[i] : ends[i + 1]].tolist()) for i in range(len(items))]
        count, total, df = len(items), sum(np.diff(ends)), Counter(t for h in held for t in h)
        if whole:
            count, total, self.longest, df = whole
        mean = max(1.0, total / max(1, count))
        posts: dict[int, list[tuple[int, float]]] = {}
        self.rest = np.zeros(len(items))  # what an item's non-essential terms are worth together
        essential: dict[int, list[tuple[int, float]]] = {}
        for i, h in enumerate(held):
            size = sum(h.values())
            raw = {t: np.log1p((count - df[t] + 0.5) / (df[t] + 0.5)) * n * (K1 + 1) / (n + K1 * (1 - B + B * size / mean)) for t, n in h.items()}
            own = sum(raw.values())
            for t, x in raw.items():
                posts.setdefault(t, []).append((i, x / own))
            for t, x in sorted(raw.items(), key=lambda p: p[1]):  # the weakest terms, up to half the threshold
                if self.rest[i] + x / own < threshold / 2:
                    self.rest[i] += x / own
                else:
                    essential.setdefault(t, []).append((i, x / own))
        self.posts = {t: (np.array([i for i, _ in p], np.int64), np.array([x for _, x in p])) for t, p in posts.items()}
        self.blocks = {t: [(int(i[k : k + BLOCK][-1]), float(x[k : k + BLOCK].max())) for k in range(0, len(i), BLOCK)] for t, (i, x) in self.posts.items()}
        self.most = {t: float(x.max()) for t, (_, x) in self.posts.items()}
        self.keys = np.array(sorted(essential), np.uint64)
        self.bits = np.zeros(1 << 20, bool)
        self.bits[(self.keys >> np.uint64(44)).astype(np.int64)] = True
        self.ptr = np.concatenate(([0], np.cumsum([len(essential[int(t)]) for t in self.keys]))).astype(np.int64)
        self.item = np.array([i for t in self.keys for i, _ in essential[int(t)]], np.int64)
        self.worth = np.array([x for t in self.keys for _, x in essential[int(t)]])
        self.parts = []
        for text in self.texts:
            w, at = words_of(text), answer_start(text)
            self.parts.append((grams(w[:at]), grams(w[at:])))

    def promising(self, hashes: np.ndarray, passage: np.ndarray) -> np.ndarray:
        """Passages in which the essential terms of some item leave it a chance; passage: the number of each word's passage."""
        maybe = np.flatnonzero(self.bits[(hashes >> np.uint64(44)).astype(np.int64)])
        at = np.searchsorted(self.keys, hashes[maybe])
        ok = at < len(self.keys)
        ok[ok] = self.keys[at[ok]] == hashes[maybe][ok]
        pair = np.unique(np.column_stack([passage[maybe[ok]], at[ok]]), axis=0) if ok.any() else np.zeros((0, 2), np.int64)
        n = self.ptr[pair[:, 1] + 1] - self.ptr[pair[:, 1]]
        if not n.sum():
            return np.zeros(0, np.int64)
        where = np.repeat(self.ptr[pair[:, 1]] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
        key = np.repeat(pair[:, 0], n) * len(self.ids) + self.item[where]
        keys, inverse = np.unique(key, return_inverse=True)
        found = np.bincount(inverse, self.worth[where]) + self.rest[keys % len(self.ids)]
        return np.unique(keys[found >= self.threshold - 1e-9] // len(self.ids))

    def search(self, terms: set[int]) -> list[tuple[int, float]]:
        """Block-max WAND: all (item, score) at or above the threshold."""
        least = self.threshold - 1e-9
        lists = [[t, 0, 0] for t in terms if t in self.posts]  # term, place, block
        out = []
        item = lambda p: int(self.posts[p[0]][0][p[1]])
        while lists:
            lists.sort(key=item)
            total, pivot = 0.0, None
            for k, p in enumerate(lists):
                total += self.most[p[0]]
                if total >= least:
                    pivot = k
                    break
            if pivot is None:
                break
            target = item(lists[pivot])
            while pivot + 1 < len(lists) and item(lists[pivot + 1]) == target:
                pivot += 1
            bound, border = 0.0, None
            for p in lists[: pivot + 1]:  # shallow moves: block maxima at the pivot
                own = self.blocks[p[0]]
                while p[2] < len(own) and own[p[2]][0] < target:
                    p[2] += 1
                if p[2] < len(own):
                    bound += own[p[2]][1]
                    border = own[p[2]][0] if border is None else min(border, own[p[2]][0])
            if bound < least:
                after = min([border if border is not None else target, *([item(lists[pivot + 1]) - 1] if pivot + 1 < len(lists) else [])]) + 1
                move, to = lists[: pivot + 1], max(after, target + 1) if after <= target else after
            elif item(lists[0]) == target:
                own = 0.0
                for p in lists[: pivot + 1]:
                    own += float(self.posts[p[0]][1][p[1]])
                if own >= least:
                    out.append((target, own))
                move, to = lists[: pivot + 1], target + 1
            else:
                move, to = lists[:pivot], target
            for p in move:
                p[1] += int(np.searchsorted(self.posts[p[0]][0][p[1] :], to))
            lists = [p for p in lists if p[1] < len(self.posts[p[0]][0])]
        return out

    def verify(self, words: list[bytes], item: int) -> tuple[float, float]:
        """Shares of the item's question and answer trigrams that the passage has."""
        joined, here = b" %b " % b" ".join(words), grams(words)
        share = lambda g: sum((x in here) if len(x) == 3 else b" %b " % b" ".join(x) in joined for x in g) / len(g) if g else 1.0
        return share(self.parts[item][0]), share(self.parts[item][1])

    def leaks(self, ids: list, texts: pa.Array, overlap: float) -> list[tuple]:
        """(doc_id, item_id, score, question overlap, answer overlap): the best passage of each pair."""
        hashes, ends = wordhash.word_hashes(texts, lower=True, punctuation=True)
        if not len(hashes) or not len(self.keys):
            return []
        stride = self.longest + 8
        n = np.diff(ends)
        steps = np.maximum(1, -(-n // stride))
        base = np.concatenate(([0], np.cumsum(steps)))
        row = np.repeat(np.arange(len(n)), n)
        step = (np.arange(len(hashes)) - ends[row]) // stride
        # A passage is two strides; each word lies in the one that starts at its stride and in the one before.
        own = base[row] + step
        early = step > 0
        at = self.promising(np.concatenate([hashes, hashes[early]]), np.concatenate([own, own[early] - 1]))
        out: dict[tuple, tuple] = {}
        last, words = -1, []
        for passage in at.tolist():
            r = int(np.searchsorted(base, passage, "right")) - 1
            lo = int(ends[r]) + (passage - int(base[r])) * stride
            hi = min(lo + 2 * stride, int(ends[r + 1]))
            for item, score in self.search(set(hashes[lo:hi].tolist())):
                if last != r:
                    last, words = r, words_of(texts[r].as_py())
                q, a = self.verify(words[lo - int(ends[r]) : hi - int(ends[r])], item)
                key = (ids[r], self.ids[item])
                if q >= overlap and a >= overlap and out.get(key, (0, 0, 0)) < (q + a, score, q):
                    out[key] = (q + a, score, q)
        return [(d, i, s, q, both - q) for (d, i), (both, s, q) in out.items()]


_LEAK = "doc_id long, item_id long, score double, question_overlap double, answer_overlap double"


def _item_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The block, the number of words and the distinct terms of each item."""
    for batch in batches:
        hashes, ends = wordhash.word_hashes(batch.column("text"), lower=True, punctuation=True)
        terms = [np.unique(hashes[a:b]).astype(np.uint64).view(np.int64) for a, b in zip(ends[:-1], ends[1:])]
        yield pa.RecordBatch.from_arrays([batch.column("block"), pa.array(np.diff(ends).astype(np.int64)), pa.array(terms, pa.list_(pa.int64()))], names=["block", "words", "terms"])


def leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.5, overlap: float = 0.5) -> DataFrame:
    """doc_id, item_id, score, question_overlap, answer_overlap of every document and test item it gives away."""
    spark = docs.sparkSession
    items = benchmark.select("item_id", "text").where(F.length("text") > 0)
    size = items.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("bytes")).first()
    blocks = max(1, -(-size["n"] // INDEX_ITEMS), -(-size["bytes"] // INDEX_BYTES))
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.length("text") > 0)
    found = spark.createDataFrame([], _LEAK)
    if blocks > 1:
        items = items.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)))
        terms = common.stored(spark, items.select("block", "text").mapInArrow(_item_terms, "block long, words long, terms array<long>"), "items")
        length = terms.agg(F.sum("words").alias("total"), F.max("words").alias("longest")).first()
        held = terms.select("block", F.explode("terms").alias("term"))
        df = common.stored(spark, held.groupBy("term").agg(F.count(F.lit(1)).alias("n")), "terms")
    for b in range(blocks):
        part, whole = items, None
        if blocks > 1:
            part = items.where(F.col("block") == b)
            own_df = held.where(F.col("block") == b).select("term").distinct().join(df, "term").collect()
            whole = size["n"], length["total"], max(1, length["longest"]), {r["term"] % (1 << 64): r["n"] for r in own_df}
        index = Index(sorted(((r["item_id"], r["text"]) for r in part.select("item_id", "text").collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1])), threshold, whole)

        def run(batches: Iterator[pa.RecordBatch], index: Index = index) -> Iterator[pa.RecordBatch]:
            for batch in (x for whole in batches for x in wordhash.slices(whole)):
                rows = index.leaks(batch.column("doc_id").to_pylist(), batch.column("text"), overlap)
                if rows:
                    kinds = [("doc_id", pa.int64()), ("item_id", pa.int64()), ("score", pa.float64()), ("question_overlap", pa.float64()), ("answer_overlap", pa.float64())]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), kinds, strict=True)], schema=pa.schema(kinds))

        found = found.union(own.mapInArrow(run, _LEAK)) if index.ids else found
    best = found.groupBy("doc_id", "item_id").agg(F.max(F.struct((F.col("question_overlap") + F.col("answer_overlap")).alias("both"), "score", "question_overlap", "answer_overlap")).alias("x"))
    return best.select("doc_id", "item_id", "x.score", "x.question_overlap", "x.answer_overlap")


def op3_decontaminate(spark, sf_dir: str) -> DataFrame:
    return leaks(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
