"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winsub.llm.common import stage


#: Edges of a file.
PART = 1_000_000


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """(a, b) edges -> (node, label): label is the smallest node of node's component.

    Every round first hangs each node's larger neighbours, then its smaller ones, below the
    smallest neighbour; it ends when a round changes nothing.  Neighbours are never gathered:
    minima are summed up before they are shuffled and meet their edges in a join, whose large
    partitions Spark splits, so a hub costs no task more than others.
    """
    now = stage(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")), "edges")
    seen = _digest(now)
    if not seen[0]:
        return now.select(F.col("a").alias("node"), F.col("b").alias("label"))
    parts = 1 + seen[0] // PART  # rounds don't add edges: few of them need few files
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = stage(large, "hung", parts)
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        now = stage(small.distinct(), "edges", parts)
        done, seen = seen, _digest(now)
        if done == seen:
            return now.select(F.col("a").alias("node"), F.col("b").alias("label"))
