"""Exact dedup with a heavy-hitter split, native DataFrame operators only.

A frequent-items sketch (Spark's ``approx_top_k``, a mergeable Misra-Gries summary of
bounded size) names the digests that may be frequent; an exact partial-aggregated count
verifies them.  The verified winners, at most ``tracked_winners`` rows, are broadcast and
decide their copies where those stand.  All other digests meet in one ordinary shuffle
of (digest, id) rows; no text is ever shuffled.

Defined results: null text counts as empty; empty texts equal each other; of equal texts
the smallest doc_id stays, null doc_ids last; of rows that repeat one doc_id and text one
stays; an empty table gives an empty result; columns of the input with clashing names
are not read, except doc_id and text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winsub.llm.common import stage, table

#: Winners kept by the sketch, and counters it tracks: fixed, so the broadcast is bounded.
WINNERS, TRACKED = 1024, 16384
#: Verified copies from which a digest counts as frequent.
FREQUENT = 64

_HUGE = "9223372036854775807"


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")


def digests(docs: DataFrame) -> DataFrame:
    """One narrow row per document, written once; ``row`` tells repeated rows apart."""
    narrow = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.sha2(normalised(F.col("text")).cast("binary"), 256).alias("text_sha256"),
    ).withColumn("row", F.monotonically_increasing_id())
    return stage(narrow, "digests")


def decide(rows: DataFrame, winners: int = WINNERS, tracked: int = TRACKED, frequent: int = FREQUENT) -> DataFrame:
    """doc_id, text_sha256, row -> the same with keep_id, group_size and kept."""
    order = F.struct(F.coalesce("doc_id", F.expr(_HUGE + "L")).alias("rank"), "row", "doc_id")
    likely = (
        rows.agg(F.expr(f"approx_top_k(text_sha256, {winners}, {tracked})").alias("top"))
        .select(F.explode("top").alias("t"))
        .select(F.col("t.item").alias("text_sha256"))
    )
    verified = (
        rows.join(F.broadcast(likely), "text_sha256")
        .groupBy("text_sha256")
        .agg(F.min(order).alias("best"), F.count(F.lit(1)).alias("group_size"))
        .where(F.col("group_size") >= frequent)
    )
    verified = stage(verified, "winners", parts=1)
    hot = rows.join(F.broadcast(verified), "text_sha256")
    same = Window.partitionBy("text_sha256")
    cold = (
        rows.join(F.broadcast(verified.select("text_sha256")), "text_sha256", "left_anti")
        .withColumn("best", F.min(order).over(same))
        .withColumn("group_size", F.count(F.lit(1)).over(same))
    )
    return hot.unionByName(cold).select(
        "doc_id",
        F.col("best.doc_id").alias("keep_id"),
        "group_size",
        (F.col("row") == F.col("best.row")).alias("kept"),
        "text_sha256",
    )


def exact_dedup(docs: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    return decide(digests(docs), **options)


def kept_documents(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, all columns; one of rows repeating doc_id and text."""
    decided = stage(exact_dedup(docs), "decided")
    lost = decided.where(~F.col("kept")).select("doc_id", "text_sha256")
    again = lost.join(decided.where("kept").select("doc_id", "text_sha256"), ["doc_id", "text_sha256"], "left_semi").limit(1)
    nulls = decided.where("doc_id is null and not kept").limit(1)
    if again.count() or nulls.count():
        # The row goes along as one value, so that no name of its own can clash.
        keep = decided.where("kept").select(F.col("doc_id").alias("id"), F.col("text_sha256").alias("sha"))
        marked = docs.select(F.struct("*").alias("whole"), F.col("doc_id").cast("long").alias("id"), F.sha2(normalised(F.col("text")).cast("binary"), 256).alias("sha"))
        held = marked.join(keep, marked.id.eqNullSafe(keep.id) & (marked.sha == keep.sha), "left_semi")
        return held.dropDuplicates(["id", "sha"]).select("whole.*")
    lost = lost.select(F.col("doc_id").alias("lost_id")).distinct()
    return docs.join(lost, docs.doc_id.cast("long") == lost.lost_id, "left_anti").select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"))


ORACLE = """
WITH d AS (
  SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id, min(doc_id) OVER g AS keep_id, CAST(count(*) OVER g AS BIGINT) AS group_size,
       doc_id = min(doc_id) OVER g AS kept, text_sha256
FROM d WINDOW g AS (PARTITION BY text_sha256)
"""
