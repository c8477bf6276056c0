"""Removal of word windows that already occurred earlier in the corpus.

Every window of `width` consecutive words gets a Rabin-Karp hash. A window is
repeated when the same word sequence also starts earlier: in a smaller doc_id,
or at an earlier place of the same document. Words covered by a repeated window
go; the covered runs are the maximal removal intervals. All windows of the
input are judged, none of what is left.

Plan: documents are dealt into chunks by a hash of doc_id (the only movement of
text, shared by both passes). The first pass keeps one occurrence of each hash
per chunk, which is what pre-aggregates a window that a third of all documents
hold, and sends 8 bytes for it to the bucket of its hash. A bucket answers each
chunk with one bit per hash: does a smaller doc_id of another chunk hold it. The
second pass hashes the chunk again and applies the bits.

Defined cases: a null text has no words; a text shorter than a window keeps all
its words; rows that share a doc_id are judged in the order of their texts, as
one document after the other; a null doc_id counts as the smallest.
"""

from __future__ import annotations

import hashlib
import math


import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, wordhash

CHUNK_BYTES = 4 << 20
BUCKET_WINDOWS = 2_000_000
_LEAST = np.iinfo(np.int64).min


def _ordered(table: pa.Table) -> tuple[pa.Table, np.ndarray]:
    """Rows by doc_id, then text; and the ids with null as the smallest number."""
    table = table.combine_chunks()
    ids = table["doc_id"].fill_null(int(_LEAST)).to_numpy(zero_copy_only=False).astype(np.int64)
    order = np.argsort(ids, kind="stable")
    if len(ids) > 1 and (np.diff(ids[order]) == 0).any():
        texts = table["text"].to_pylist()
        order = np.array(sorted(range(len(ids)), key=lambda i: (ids[i], texts[i] or "")), np.int64)
    return table.take(pa.array(order)), ids[order]


def _first_of_chunk(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each window, the place of the first equal one in this chunk; and the places that are first, ascending."""
    order = np.argsort(hashes, kind="stable")
    new = np.ones(len(hashes), bool)
    new[1:] = hashes[order][1:] != hashes[order][:-1]
    leads = order[new]
    lead = np.empty(len(hashes), np.int64)
    lead[order] = np.repeat(leads, np.diff(np.append(np.flatnonzero(new), len(hashes))))
    return lead, np.sort(leads)


def _scan(table: pa.Table, width: int, buckets: int):
    table, ids = _ordered(table)
    words, ends = wordhash.word_hashes(table["text"])
    hashes, index, ptr = wordhash.windows(words, ends, width)
    lead, leads = _first_of_chunk(hashes)
    bucket = (hashes[leads] % np.uint64(buckets)).astype(np.int64)
    by_bucket = np.argsort(bucket, kind="stable")
    cuts = np.searchsorted(bucket[by_bucket], np.arange(buckets + 1))
    row = np.searchsorted(ptr, leads, "right") - 1
    return table, ids, ends, hashes, index, lead, leads, row, by_bucket, cuts


def _send(table: pa.Table, width: int, buckets: int) -> pa.Table:
    chunk = table["chunk"][0].as_py()
    _, ids, _, hashes, _, _, leads, row, by_bucket, cuts = _scan(table, width, buckets)
    out: dict[str, list] = {"bucket": [], "chunk": [], "hashes": [], "docs": [], "counts": []}
    for b in range(buckets):
        own = by_bucket[cuts[b] : cuts[b + 1]]
        if len(own):
            at, n = np.unique(row[own], return_counts=True)
            out["bucket"].append(b)
            out["chunk"].append(chunk)
            out["hashes"].append(hashes[leads[own]].tobytes())
            out["docs"].append(np.diff(ids[at], prepend=np.int64(0)).tobytes() if len(at) else b"")
            out["counts"].append(n.astype(np.uint32).tobytes())
    return pa.table(out, schema=_SENT)


_SENT = pa.schema([("bucket", pa.int32()), ("chunk", pa.int64()), ("hashes", pa.binary()), ("docs", pa.binary()), ("counts", pa.binary())])
_ANSWER = pa.schema([("chunk", pa.int64()), ("bucket", pa.int32()), ("bits", pa.binary())])


def _judge(table: pa.Table) -> pa.Table:
    """One bit per hash and chunk: a smaller doc_id of another chunk holds it."""
    hashes, docs, sizes = [], [], []
    for h, d, n in zip(table["hashes"], table["docs"], table["counts"], strict=True):
        hashes.append(np.frombuffer(h.as_py(), np.uint64))
        docs.append(np.repeat(np.cumsum(np.frombuffer(d.as_py(), np.int64)), np.frombuffer(n.as_py(), np.uint32)))
        sizes.append(len(hashes[-1]))
    every, owner = np.concatenate(hashes), np.concatenate(docs)
    del hashes, docs
    order = np.argsort(every)
    run = every[order]
    begins = np.flatnonzero(np.concatenate(([True], run[1:] != run[:-1])))
    least = np.minimum.reduceat(owner[order], begins)
    late = np.empty(len(every), bool)
    late[order] = owner[order] > np.repeat(least, np.diff(np.append(begins, len(run))))
    parts = np.split(late, np.cumsum(sizes)[:-1])
    keep = [i for i, x in enumerate(parts) if x.any()]
    b = table["bucket"][0].as_py()
    return pa.table({"chunk": [table["chunk"][i].as_py() for i in keep], "bucket": [b] * len(keep), "bits": [np.packbits(parts[i]).tobytes() for i in keep]}, schema=_ANSWER)


def _apply(left: pa.Table, right: pa.Table, width: int, buckets: int, out: pa.Schema) -> pa.Table:
    if not left.num_rows:
        return out.empty_table()
    table, _, ends, hashes, index, lead, leads, _, by_bucket, cuts = _scan(left, width, buckets)
    late = np.zeros(len(hashes), bool)
    for b, bits in zip(right["bucket"].to_pylist(), right["bits"].to_pylist(), strict=True):
        own = leads[by_bucket[cuts[b] : cuts[b + 1]]]
        late[own] = np.unpackbits(np.frombuffer(bits, np.uint8), count=len(own)).astype(bool)
    gone = late[lead] | (lead != np.arange(len(lead)))
    cover = np.zeros(int(ends[-1]) + 1, np.int64)
    cover[index[gone]] += 1
    cover[index[gone] + width] -= 1
    covered = np.cumsum(cover[:-1]) > 0
    n_removed, spans, kept = [], [], []
    texts = table["text"].to_pylist()
    for i, text in enumerate(texts):
        own = covered[ends[i] : ends[i + 1]]
        n_removed.append(int(own.sum()))
        words = (text or "").encode().split()
        if n_removed[-1]:
            edges = np.flatnonzero(np.diff(np.concatenate(([False], own, [False])).astype(np.int8)))
            spans.append(edges.reshape(-1, 2).tolist())
            words = [w for w, x in zip(words, own.tolist(), strict=True) if not x]
        else:
            spans.append([])
        kept.append(b" ".join(words))
    n_words = np.diff(ends)
    made = {"doc_id": table["doc_id"], "n_words": n_words, "n_removed": n_removed, "kept_sha256": [hashlib.sha256(x).hexdigest() for x in kept]}
    if "removed" in out.names:
        made |= {"removed": spans, "kept_text": [x.decode("utf-8") for x in kept]}
    return pa.table([pa.array(made[f.name], f.type) if not isinstance(made[f.name], pa.ChunkedArray) else made[f.name].cast(f.type) for f in out], schema=out)


def remove_repeated_windows(docs: DataFrame, width: int = 20, texts: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and, if texts, the removed word intervals [from, to) and the kept text."""
    spark = docs.sparkSession
    size = common.text_bytes(docs)
    chunks = max(1, math.ceil(size / CHUNK_BYTES))
    buckets = max(16, math.ceil(size / 6 / BUCKET_WINDOWS))
    dealt = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(chunks)).alias("chunk")).repartition(common.partitions(spark), "chunk")
    out = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())]
    ddl = "doc_id long, n_words long, n_removed long, kept_sha256 string"
    if texts:
        out += [("removed", pa.list_(pa.list_(pa.int64()))), ("kept_text", pa.string())]
        ddl += ", removed array<array<long>>, kept_text string"
    schema = pa.schema(out)
    sent = dealt.groupBy("chunk").applyInArrow(lambda t: _send(t, width, buckets), "bucket int, chunk long, hashes binary, docs binary, counts binary")
    answers = sent.groupBy("bucket").applyInArrow(_judge, "chunk long, bucket int, bits binary")
    return dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(lambda a, b: _apply(a, b, width, buckets, schema), ddl)


def op10_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeated_windows(common.table(spark, sf_dir, "documents"), texts=False)




OP10_SQL = """
WITH d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS words FROM documents
), win AS (
  SELECT doc_id, i, array_to_string(words[i:i + 19], ' ') AS k FROM (SELECT doc_id, words, unnest(range(1, len(words) - 18)) AS i FROM d)
), gone AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY k ORDER BY doc_id, i) AS n FROM win) WHERE n > 1
), cover AS (
  SELECT doc_id, list(DISTINCT p) AS ps FROM (SELECT doc_id, unnest(range(i, i + 20)) AS p FROM gone) GROUP BY doc_id
), kept AS (
  SELECT doc_id, string_agg(w, ' ' ORDER BY p) AS t
  FROM (SELECT doc_id, unnest(words) AS w, unnest(range(1, len(words) + 1)) AS p FROM d) x
  ANTI JOIN (SELECT doc_id, unnest(ps) AS p FROM cover) y USING (doc_id, p) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(len(ps), 0) AS BIGINT) AS n_removed,
       sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN cover USING (doc_id) LEFT JOIN kept USING (doc_id)
"""
