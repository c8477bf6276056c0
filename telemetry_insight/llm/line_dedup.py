"""Line deduplication by keep bitmaps [native].

A line's key is the line without ASCII white space at both ends and with A-Z
lower-cased. Keys of at least `min_chars` code points found in at least
`min_docs` documents lose all their lines except those of the largest doc_id
that holds the key.

Plan: each long line yields a row of the key's 64-bit hash, document and
position; no text moves. Rows go to ranges of (hash, document), sorted there by
hash, document and position, and stream into one row for each first occurrence of
a key in a document, which carries the sorted places of the later ones. A key's holders
are these rows, counted in partial counts, so a line that
a third of the documents share arrives as a few rows, and the join that reads
the counts back is of the kind whose hot partitions Spark splits. What comes
back to a document is a run-length keep bitmap.

Defined cases: a null or empty text is one empty line; rows that share a doc_id
are one document for the counts and each gets the bitmap of its own lines; a
null doc_id counts as the smallest document and keeps its null. Two keys share
a 64-bit hash with a chance of 2**-64.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

_STRIP = f"^[{common.BLANK}]+|[{common.BLANK}]+$"


def lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_key(line: Column) -> Column:
    return common.ascii_lower(F.regexp_replace(line, _STRIP, ""))


def line_hits(docs: DataFrame, min_chars: int = 20) -> DataFrame:
    """row_key, doc_id, hash, positions: one row for each document and distinct long key."""
    keyed = docs.select(
        F.xxhash64("text").alias("row_key"),
        F.coalesce("doc_id", F.lit(-(1 << 63))).alias("doc_id"),
        F.posexplode(lines(F.col("text"))).alias("pos", "line"),
    )
    key = line_key(F.col("line"))
    return keyed.select("row_key", "doc_id", "pos", key.alias("key")).where(F.length("key") >= min_chars).select("row_key", "doc_id", "pos", F.xxhash64("key").alias("hash"))


def line_bitmaps(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """doc_id, row_key, n_lines, n_dropped, dropped: for documents that lose lines, the sorted runs [from, to) of dropped line numbers."""
    spark = docs.sparkSession
    hits = common.stored(spark, line_hits(docs, min_chars), "line-hits")
    # Ranges of (hash, document): a key that very many documents hold spans several of them.
    ranged = hits.repartitionByRange(common.partitions(spark), "hash", "doc_id").sortWithinPartitions("hash", "doc_id", "pos")
    firsts = common.stored(spark, ranged.groupBy("hash", "doc_id").agg(F.collect_list(F.struct("row_key", "pos")).alias("at")), "line-firsts")
    counted = firsts.groupBy("hash").agg(F.count(F.lit(1)).alias("holders"), F.max("doc_id").alias("keeper")).where(F.col("holders") >= min_docs)
    holders = common.stored(spark, counted, "line-holders")  # stored, so that both sides of the join are plain exchanges, whose hot partitions Spark splits
    lost = firsts.join(holders, "hash").where(F.col("doc_id") < F.col("keeper")).select("doc_id", F.inline("at"))
    drops = lost.groupBy("doc_id", "row_key").agg(F.array_sort(F.collect_set("pos")).alias("at"))
    return drops.select("doc_id", "row_key", F.size("at").cast("long").alias("n_dropped"), runs(F.col("at")).alias("dropped"))


def runs(at: Column) -> Column:
    """Sorted distinct integers as runs of struct<from, to>, to exclusive: a compressed bitmap."""
    begins = F.filter(at, lambda x, i: (i == 0) | (F.get(at, i - 1) != x - 1))
    ends = F.filter(at, lambda x, i: (i == F.size(at) - 1) | (F.get(at, i + 1) != x + 1))
    return F.transform(begins, lambda x, i: F.struct(x.alias("from"), (F.get(ends, i) + 1).alias("to")))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame) -> DataFrame:
    """docs with n_lines, n_dropped, dropped and kept_text, in place of columns of docs of these names; every row and every other column stays."""
    columns = [c for c in docs.columns if c.lower() not in ("n_lines", "n_dropped", "dropped", "kept_text")]
    key, row = common.fresh("_id", columns), common.fresh("_row", columns)
    own = docs.select(*columns).withColumns({key: F.coalesce("doc_id", F.lit(-(1 << 63))), row: F.xxhash64("text")})
    found = bitmaps.select(F.col("doc_id").alias(key), F.col("row_key").alias(row), "n_dropped", "dropped")
    joined = own.hint("shuffle_hash").join(found.hint("shuffle_hash"), [key, row], "left")
    all_lines = lines(F.col("text"))
    # The runs kept between the dropped ones, each cut out as one slice.
    starts = F.concat(F.array(F.lit(0)), F.transform("dropped", lambda r: r["to"]))
    stops = F.concat(F.transform("dropped", lambda r: r["from"]), F.array(F.size(all_lines)))
    kept = F.flatten(F.transform(F.arrays_zip(starts.alias("a"), stops.alias("b")), lambda r: F.slice(all_lines, r["a"] + 1, r["b"] - r["a"])))
    return joined.select(
        *columns,
        F.size(all_lines).cast("long").alias("n_lines"),
        F.coalesce("n_dropped", F.lit(0)).cast("long").alias("n_dropped"),
        F.coalesce("dropped", F.array().cast("array<struct<from:int,to:int>>")).alias("dropped"),
        F.when(F.col("dropped").isNull(), F.coalesce("text", F.lit(""))).otherwise(F.array_join(kept, "\n")).alias("kept_text"),
    )


def op1_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    return apply_bitmaps(docs, line_bitmaps(docs)).select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


OP1_SQL = """
WITH l AS (
  SELECT doc_id, unnest(ls) AS line, unnest(range(len(ls))) AS pos
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents)
), k AS (
  SELECT doc_id, pos, line, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
         'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l
), h AS (
  SELECT key, count(DISTINCT doc_id) AS n, max(doc_id) AS keeper FROM k WHERE length(key) >= 20 GROUP BY key
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (coalesce(n, 0) >= 3 AND doc_id <> keeper) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT (coalesce(n, 0) >= 3 AND doc_id <> keeper)), '')) AS kept_sha256
FROM k LEFT JOIN h USING (key) GROUP BY doc_id
"""
