"""Windows over integer alphabets: lists of dictionary codes instead of characters."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from winsub.kernel.window_index import WindowIndex
from winsub.model import MATCHES, names


def code_windows(coded: DataFrame, capacity: int) -> DataFrame:
    """(stream_id, seq, code) -> (stream_id, n_seen, codes): each stream's last codes, chosen before they are gathered."""
    seen = coded.groupBy("stream_id").agg(F.count(F.lit(1)).alias("n_seen"))
    back = F.row_number().over(Window.partitionBy("stream_id").orderBy(F.desc("seq")))
    last = coded.select("stream_id", "seq", "code", back.alias("back")).where(F.col("back") <= capacity)
    codes = F.transform(F.array_sort(F.collect_list(F.struct("seq", "code"))), lambda x: x["code"])
    return last.groupBy("stream_id").agg(codes.alias("codes")).join(seen, "stream_id")


def locate_codes(coded: DataFrame, dictionary: DataFrame, patterns: list[tuple[str, list]], capacity: int) -> DataFrame:
    """Coded symbols and patterns (query_id, symbols) -> MATCHES; a symbol that the dictionary lacks occurs nowhere."""
    wanted = sorted({x for _, p in patterns for x in p})
    code = {r["sym"]: r["code"] for r in dictionary.where(F.col("sym").isin(wanted)).collect()}  # the patterns' symbols at most
    asked = [(q, [code[x] for x in p]) for q, p in patterns if all(x in code for x in p)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, n, codes in zip(b.stream_id, b.n_seen, b.codes, strict=True):
                index = WindowIndex(max(1, len(codes)))
                index.start = index.n_seen = index._base = n - len(codes)
                index.extend(int(c) for c in codes)
                out += [(sid, q, n, off) for q, p in asked for off in index.locate(p, ordered=False)]
            yield pd.DataFrame(out, columns=names(MATCHES))

    return code_windows(coded, capacity).select("stream_id", "n_seen", "codes").mapInPandas(run, MATCHES)
