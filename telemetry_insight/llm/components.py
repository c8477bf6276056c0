"""Connected components of an edge list, by alternating large-star and small-star rounds.

Each round is one aggregation and one join over edges; a node that a third of
all edges touch is reduced in partial minima, and the join's hot partitions are
of the kind Spark splits. Edges of a round are stored in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _star(both: DataFrame, large: bool) -> DataFrame:
    """both: directed edges (u, v). New edges from neighbours to the least node around u."""
    if not large:
        both = both.where(F.col("v") < F.col("u"))
    least = common.stored(both.sparkSession, both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "star")
    joined = both.join(least, "u")
    if large:
        return joined.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    to = joined.where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return to.union(least.select("u", F.col("m").alias("v")))


def components(edges: DataFrame) -> DataFrame:
    """node, component of every node of edges (a, b): the least node it can reach."""
    spark = edges.sparkSession
    now = common.stored(spark, edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    mark = None
    while True:
        seen = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (seen["n"], seen["h"]) == mark or not seen["n"]:
            break
        mark = (seen["n"], seen["h"])
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = common.stored(spark, _star(both, True).distinct(), "edges")
        now = common.stored(spark, _star(large, False).where("u <> v").distinct(), "edges")
    heads = now.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
    return common.stored(spark, now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(heads), "components")
