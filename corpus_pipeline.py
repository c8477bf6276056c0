"""A corpus pipeline over documents: filter, deduplicate, decontaminate, encode.

Each stage takes (spark, docs, sf_dir) and works on all rows the stage before kept.
All but the last return the columns of documents. run() writes each stage's
rows as Parquet in the shared folder and reads them again for the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from telemetry_insight.llm import common, decontaminate, jaccard_join, line_dedup, piece_lattice, toxicity


def _lean(docs: DataFrame) -> tuple[DataFrame, str]:
    """doc_id, text and the other columns in one, whose name is returned: whatever they are called, they meet no column of an operator."""
    rest, name = [c for c in docs.columns if c not in ("doc_id", "text")], common.fresh("rest", docs.columns)
    return docs.select("doc_id", "text", F.struct(F.lit(0).alias(common.fresh("none", rest)), *rest).alias(name)), name


def _as_documents(rows: DataFrame, docs: DataFrame, rest: str, text: str = "text") -> DataFrame:
    """The columns of docs with another text; a null text stays null."""
    new = F.when(F.col("text").isNotNull(), F.col(text))
    size = lambda c: F.length(new).cast(docs.schema[c].dataType) if text != "text" else F.col(rest)[c]
    return rows.select(*[new.alias("text") if c == "text" else F.col("doc_id") if c == "doc_id" else size(c).alias(c) if c == "n_chars" else F.col(rest)[c].alias(c) for c in docs.columns])


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below 0.5."""
    lean, rest = _lean(docs)
    return _as_documents(toxicity.score(lean, common.table(spark, sf_dir, "labels")).where("predicted = 0"), docs, rest)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, without the lines that it shares with others and is not the keeper of."""
    lean, rest = _lean(docs)
    return _as_documents(line_dedup.apply_bitmaps(lean, line_dedup.line_bitmaps(lean)), docs, rest, "kept_text")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group; documents without an id stay."""
    groups = jaccard_join.near_components(docs).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(groups, "doc_id", "left_anti").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that give no test item away."""
    leaks = decontaminate.leaks(docs, common.table(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.join(leaks, "doc_id", "left_anti").select(*docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_pieces and ids of every document."""
    coded = piece_lattice.encode(docs, piece_lattice.Pieces.load())
    return coded.select("doc_id", F.coalesce(F.when(F.col("ids").isNotNull(), F.size("ids")), F.lit(0)).cast("long").alias("n_pieces"), "ids")


STAGES = [
    ("toxicity", toxicity_filter),
    ("line dedup", drop_repeated_lines),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("SentencePiece encoding", encode),
]

#: The stages aren't SQL; the tests compare run() with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = common.stored(spark, stage(spark, docs, sf_dir), "stage")
    return docs
