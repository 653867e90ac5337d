"""Which method answers, and how windows meet queries.

Everything here is decided from the tables' own sizes, checked before use: a query set is
sent to all tasks only if it has at most ``SENT_QUERIES`` patterns and ``SENT_SYMBOLS``
symbols; beyond that windows and patterns meet in an equi-join on a q-gram.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SENT_QUERIES, SENT_SYMBOLS = 20_000, 8_000_000

#: Relative cost of a symbol scanned natively, indexed by the kernel, put in a suffix array.
SCAN, BUILD, SORT = 1.0, 3000.0, 120.0


def choose_method(queries: int, window: float, frozen: bool = True) -> str:
    """Native scan, static suffix array, or the live index, by estimated work a window."""
    scan = queries * window * SCAN
    sort = window * SORT + queries * 40
    build = window * BUILD + queries * 40
    if frozen:
        return "native" if scan <= sort else "suffix_array"
    return "native" if scan <= min(build, sort * max(1.0, window / 64)) else "index"


def sendable(queries: DataFrame) -> list[tuple[str, str]] | None:
    """(query_id, pattern) of queries for all streams if the set is within the bounds."""
    if queries.where("stream_id is not null").limit(1).count():
        return None
    rows = queries.where("pattern is not null").select("query_id", "pattern").limit(SENT_QUERIES + 1)
    size = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.length("pattern")), F.lit(0))).first()
    if size[0] > SENT_QUERIES or size[1] > SENT_SYMBOLS:
        return None
    return [(r["query_id"], r["pattern"]) for r in rows.collect()]


def gram_pairs(windows: DataFrame, queries: DataFrame, q: int = 8) -> DataFrame:
    """(window columns, query_id, pattern) of pairs that share the pattern's first q-gram.

    Patterns shorter than ``q`` are grouped by their length, one join for each length.
    """
    queries = queries.where("length(pattern) > 0").withColumn("m", F.least(F.length("pattern"), F.lit(q)))
    lengths = [r["m"] for r in queries.select("m").distinct().collect()]  # at most q rows
    out = None
    for m in sorted(lengths):
        own = queries.where(F.col("m") == m).select("query_id", F.col("stream_id").alias("only"), "pattern", F.left("pattern", F.lit(m)).alias("gram"))
        # Grams go without their windows: of a window only its key is repeated.
        grams = windows.where(F.length("win_text") >= m).select("stream_id", "n_seen", F.explode(F.array_distinct(F.expr(f"transform(sequence(1, length(win_text) - {m - 1}), i -> substring(win_text, i, {m}))"))).alias("gram"))
        met = grams.join(own, "gram").where("only is null or only = stream_id").drop("gram", "only")
        out = met if out is None else out.unionByName(met)
    if out is None:
        out = windows.select("stream_id", "n_seen").join(queries.select("query_id", "pattern"), F.lit(False))
    return windows.join(out, ["stream_id", "n_seen"]).where(F.contains("win_text", "pattern"))


def gram_signature(text: str, q: int = 3, bits: int = 4096) -> bytes:
    """Which q-grams a text may have: a bit set by a fixed rolling hash."""
    code = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)
    n = max(0, len(code) - q + 1)
    h = np.zeros(n, np.uint64)
    for k in range(q):
        h = (h * np.uint64(1_000_003) + code[k : k + n]) & np.uint64(0xFFFFFFFF)
    flags = np.zeros(bits, bool)
    flags[(h ^ h >> np.uint64(15)) % np.uint64(bits)] = True
    return np.packbits(flags, bitorder="little").tobytes()


def may_contain(sig: bytes, pattern_sig: bytes) -> bool:
    a, b = int.from_bytes(sig, "little"), int.from_bytes(pattern_sig, "little")
    return a & b == b
