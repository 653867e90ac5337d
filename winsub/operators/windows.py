"""Windows over texts, and query tables."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.model import QUERIES


def window_at(rows: DataFrame, capacity: int, every: int | None = None) -> DataFrame:
    """The last ``capacity`` symbols of every text; with ``every``, at each such position too.

    The window is cut before anything is expanded by symbol.
    """
    if capacity < 1:
        raise ValueError("capacity must be at least 1")
    if every is None:
        cut = rows.select("stream_id", F.length("text").cast("long").alias("n_seen"), F.expr(f"right(text, {capacity})").alias("win_text"))
    else:
        at = F.expr(f"explode(sequence({every}, length(text), {every}))").alias("n")
        cut = rows.where(F.length("text") >= every).select("stream_id", "text", at)
        cut = cut.select("stream_id", F.col("n").cast("long").alias("n_seen"), F.expr(f"substring(text, greatest(n - {capacity}, 0) + 1, least(n, {capacity}))").alias("win_text"))
    return cut.select("stream_id", "n_seen", (F.col("n_seen") - F.length("win_text")).alias("win_start"), "win_text")


def make_queries(spark: SparkSession, patterns: Iterable[str]) -> DataFrame:
    patterns = list(patterns)
    if any(not p for p in patterns):
        raise ValueError("an empty pattern")
    return spark.createDataFrame([(p, None, p, None) for p in patterns], QUERIES)


def queries_from(df: DataFrame, id_: str, text: str) -> DataFrame:
    """A query for every row; empty and null patterns give none."""
    return df.where(F.length(F.expr(text)) > 0).select(F.expr(f"cast({id_} as string)").alias("query_id"), F.lit(None).cast("string").alias("stream_id"), F.expr(text).alias("pattern"), F.lit(None).cast("long").alias("at_seq"))


def sample_queries(rows: DataFrame, lengths: list[int], per_stream: int) -> DataFrame:
    """Substrings of each text at places drawn from a digest of the stream's id: repeatable."""
    k, m = F.explode(F.sequence(F.lit(0), F.lit(per_stream - 1))).alias("k"), F.explode(F.array(*map(F.lit, lengths))).alias("m")
    drawn = rows.select("stream_id", "text", k).select("*", m).where("length(text) >= m")
    place = F.expr("cast(conv(left(md5(concat_ws(':', stream_id, k, m)), 8), 16, 10) as bigint) % (length(text) - m + 1)")
    drawn = drawn.withColumn("at", place)
    return drawn.select(F.concat_ws(":", "stream_id", "k", "m").alias("query_id"), "stream_id", F.expr("substring(text, cast(at as int) + 1, m)").alias("pattern"), F.lit(None).cast("long").alias("at_seq"))
