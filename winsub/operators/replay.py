"""The index run over whole streams: answers and tails as of many positions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame

from winsub.kernel.window_index import WindowIndex
from winsub.model import MATCHES, TAILS, names


def replay_matches(rows: DataFrame, capacity: int, patterns: list[str], every: int, rule: str = "project") -> DataFrame:
    """(stream_id, text) -> MATCHES at every ``every``-th position; one index a stream."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for sid, text in zip(b.stream_id, b.text, strict=True):
                index, out = WindowIndex(capacity), []
                for n, sym in enumerate(text, 1):
                    index.push(sym)
                    if n % every == 0:
                        out += [(sid, p, n, off) for p in patterns for off in index.locate(p, rule, ordered=False)]
                yield pd.DataFrame(out, columns=names(MATCHES))

    return rows.select("stream_id", "text").mapInPandas(run, MATCHES)


def replay_tails(rows: DataFrame, capacity: int, every: int = 1) -> DataFrame:
    """(stream_id, text) -> TAILS after every ``every``-th symbol."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for sid, text in zip(b.stream_id, b.text, strict=True):
                index, out = WindowIndex(capacity), []
                for n, sym in enumerate(text, 1):
                    index.push(sym)
                    if n % every == 0:
                        found = index.tail_period() or (None, None)
                        out.append((sid, n, index.tail_start, index.tail_len, index.cursor_kind(), *found))
                yield pd.DataFrame(out, columns=names(TAILS)).astype({"twin": "Int64", "period": "Int64"})

    return rows.select("stream_id", "text").mapInPandas(run, TAILS)


EFFECT = "stream_id string, before bigint, after bigint, outcome string, kids bigint"


def evict_effect(windows: DataFrame) -> DataFrame:
    """The tail before and after dropping the oldest symbol, the way it was dropped, and how
    many children the oldest leaf's parent had."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.win_text, strict=True):
                if not text:
                    continue
                index = WindowIndex(len(text)).extend(text)
                before, kids = index.tail_len, len(index.kids[index.up[index.leaf_at[index.start]]])
                outcome = index._evict_oldest()
                out.append((sid, before, index.tail_len, outcome, kids))
            yield pd.DataFrame(out, columns=names(EFFECT))

    return windows.where("win_text is not null").select("stream_id", "win_text").mapInPandas(run, EFFECT)
