"""Very long streams as sealed segments: pruned by signature, searched apart, joined at seams.

A match belongs to the segment its start lies in, so none is found twice.  A segment
carries the first ``overlap`` symbols of what follows; longer patterns are found by their
first ``overlap + 1`` symbols and checked against the next segments by a join.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.kernel.scan import native_find
from winsub.kernel.static_index import suffix_array
from winsub.model import MATCHES, SEGMENTS, names
from winsub.plans.planner import gram_signature, may_contain, sendable


def seal_segments(chunks: DataFrame, max_pattern: int, hot: bool = False) -> DataFrame:
    """CHUNKS (all of a stream's of one size >= max_pattern - 1) -> SEGMENTS; ``hot`` ones get a suffix array."""
    # A chunk sends its first symbols to the one before it; nothing else of a stream meets.
    own = F.struct("chunk_no", "base_off", "text", F.lit(None).cast("string").alias("overlap"))
    head = F.struct((F.col("chunk_no") - 1).alias("chunk_no"), F.lit(None).cast("long").alias("base_off"), F.lit(None).cast("string").alias("text"), F.left("text", F.lit(max_pattern - 1)).alias("overlap"))
    rows = chunks.select("stream_id", F.explode(F.array(own, head)).alias("c")).select("stream_id", "c.*").groupBy("stream_id", F.col("chunk_no").alias("seg_no"))
    rows = rows.agg(F.max("base_off").alias("base_off"), F.max("text").alias("text"), F.coalesce(F.max("overlap"), F.lit("")).alias("overlap")).where("text is not null")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            whole = [t + o for t, o in zip(b.text, b.overlap, strict=True)]
            b["sig"] = [gram_signature(w) for w in whole]
            b["sa"] = [suffix_array(w).astype(np.int32).tobytes() if hot else None for w in whole]
            yield b[names(SEGMENTS)]

    return rows.mapInPandas(run, SEGMENTS)


def expire_segments(segments: DataFrame, capacity: int) -> DataFrame:
    """Segments (or chunks) that reach into their stream's last ``capacity`` symbols; only metadata decides."""
    end = F.col("base_off") + F.length("text")
    seen = segments.groupBy("stream_id").agg(F.max(end).alias("n_seen"))
    return segments.join(seen, "stream_id").where(end > F.col("n_seen") - capacity).drop("n_seen")


BUCKETS = 64


def write_index(segments: DataFrame, path: str, buckets: int = BUCKETS) -> None:
    """SEGMENTS to Parquet, one folder for each bucket of streams; long streams spread over files."""
    rows = segments.select(*names(SEGMENTS), F.pmod(F.xxhash64("stream_id"), F.lit(buckets)).cast("int").alias("bucket"))
    rows.write.partitionBy("bucket").parquet(path)


def read_index(spark: SparkSession, path: str, streams: list[str] | None = None, buckets: int = BUCKETS) -> DataFrame:
    """SEGMENTS of a store; of ``streams`` only, whose folders alone are read."""
    rows = spark.read.schema(SEGMENTS + ", bucket int").parquet(path)
    if streams is not None:
        kept = spark.createDataFrame([(x,) for x in streams], "stream_id string").select("stream_id", F.pmod(F.xxhash64("stream_id"), F.lit(buckets)).cast("int").alias("bucket"))
        rows = rows.where(F.col("bucket").isin([r["bucket"] for r in kept.collect()]) & F.col("stream_id").isin(streams))
    return rows.select(*names(SEGMENTS))


def locate_segmented(segments: DataFrame, queries: DataFrame, max_pattern: int, capacity: int | None = None) -> DataFrame:
    """SEGMENTS, QUERIES for all streams -> MATCHES over whole streams or their last ``capacity`` symbols."""
    sent = sendable(queries)
    if sent is None:
        raise ValueError("too many queries to send: split them, or use locate with an equi-join")
    seeds = [(q, p[:max_pattern], len(p), gram_signature(p[:max_pattern])) for q, p in sent]

    def find(text: str, sa: bytes | None, p: str) -> list[int]:
        if sa is None:
            return native_find(text, p)[0]
        order, m = np.frombuffer(sa, np.int32), len(p)
        lo, hi = 0, len(order)
        while lo < hi:
            mid = (lo + hi) // 2
            lo, hi = (mid + 1, hi) if text[order[mid] : order[mid] + m] < p else (lo, mid)
        end = lo
        while end < len(order) and text.startswith(p, order[end]):
            end += 1
        return order[lo:end].tolist()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, no, base, text, over, sig, sa in zip(b.stream_id, b.seg_no, b.base_off, b.text, b.overlap, b.sig, b.sa, strict=True):
                whole = text + over
                for q, seed, _, own in seeds:
                    if may_contain(sig, own):
                        out += [(sid, q, no, base + i) for i in find(whole, sa, seed) if i < len(text)]
            yield pd.DataFrame(out, columns=["stream_id", "query_id", "seg_no", "off"])

    hits = segments.select(*names(SEGMENTS)).mapInPandas(run, "stream_id string, query_id string, seg_no bigint, off bigint")
    q = F.broadcast(queries.select("query_id", "pattern"))
    hits = hits.join(q, "query_id")
    short = hits.where(F.length("pattern") <= max_pattern).select("stream_id", "query_id", "off")
    long_ = hits.where(F.length("pattern") > max_pattern)
    # The rest of a long pattern: the segments it reaches into, put together.
    last = F.floor((F.col("off") + F.length("pattern") - 1) / F.col("size")).cast("long")
    size = segments.groupBy("stream_id").agg(F.max(F.length("text")).alias("size"), F.max(F.col("base_off") + F.length("text")).alias("n_seen"))
    need = long_.join(size, "stream_id").withColumn("no", F.explode(F.sequence("seg_no", last)))
    met = need.join(segments.select("stream_id", F.col("seg_no").alias("no"), "base_off", "text"), ["stream_id", "no"])
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("no", "text"))), lambda x: x["text"]), "")
    met = met.groupBy("stream_id", "query_id", "pattern", "off").agg(text.alias("text"), F.min("base_off").alias("base"))
    checked = met.where(F.expr("substring(text, cast(off - base as int) + 1, length(pattern)) = pattern")).select("stream_id", "query_id", "off")
    found = short.unionByName(checked).join(size.drop("size"), "stream_id")
    if capacity is not None:
        found = found.where(F.col("off") >= F.col("n_seen") - capacity)
    return found.select(*names(MATCHES))
