"""What a filter keeps of a stream whose text is let go."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winsub.plans.planner import gram_signature

#: Symbols of texts that are counted together; a longer text is counted in stretches of so many.
TOGETHER = 1 << 17

GRAMS = "stream_id string, gram string, cnt bigint"


def _summed(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order and how often, or with ``counts`` how much, each stands there."""
    if counts is None:
        keys = np.sort(keys)
    else:
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    if counts is None:
        return keys[first], np.diff(np.append(first, len(keys)))
    return keys[first], np.add.reduceat(counts, first)


def _strings(code: np.ndarray, q: int) -> pa.Array:
    """Strings of ``q`` code points each, put one after the other in ``code``."""
    if not len(code) or code.max() < 128:
        width, data = np.full(len(code) // q, q, np.int32), code.astype(np.uint8).tobytes()
    else:
        wide = 1 + (code > 0x7F) + (code > 0x7FF) + (code > 0xFFFF)
        width, data = wide.reshape(-1, q).sum(1).astype(np.int32), code.astype("<u4").tobytes().decode("utf-32-le").encode()
    ends = np.zeros(len(width) + 1, np.int32)
    np.cumsum(width, out=ends[1:])
    return pa.StringArray.from_buffers(len(width), pa.py_buffer(ends), pa.py_buffer(data))


def count_grams(texts: list[str], q: int) -> Iterator[tuple[np.ndarray, pa.Array, np.ndarray]]:
    """(places of texts, grams, counts): each text's distinct q-grams once, a long text's after the others."""
    code = np.frombuffer("".join(texts).encode("utf-32-le"), "<u4")
    known = np.zeros(0x110000, bool)
    known[code] = True
    letters = np.flatnonzero(known).astype(np.uint32)
    at = np.zeros(0x110000, np.uint32)
    at[letters] = np.arange(len(letters), dtype=np.uint32)
    size = np.array([len(t) for t in texts], np.int64)
    end = np.cumsum(size)
    base = max(2, len(letters))
    if base**q * len(texts) >= 1 << 63:
        yield from _count_wide(texts, q)
        return
    keys, counts = [], []
    for k in range(0, len(code) - q + 1, TOGETHER):
        part = at[code[k : k + TOGETHER + q - 1]].astype(np.int64)
        begin = np.arange(k, k + len(part) - q + 1)
        doc = np.repeat(np.arange(len(size)), size)[k : k + len(begin)] if len(texts) > 1 else np.zeros(len(begin), np.int64)
        key = doc.copy()
        for j in range(q):
            key *= base
            key += part[j : j + len(begin)]
        key, n = _summed(key[begin + q <= end[doc]])  # a gram lies in one text
        keys.append(key)
        counts.append(n)
        if len(keys) > 1:
            key, n = _summed(np.concatenate(keys), np.concatenate(counts))
            keys, counts = [key], [n]
    if not keys or not len(keys[0]):
        return
    for k in range(0, len(keys[0]), TOGETHER):
        key, n = keys[0][k : k + TOGETHER], counts[0][k : k + TOGETHER]
        out = np.empty((len(key), q), np.uint32)
        for j in range(q - 1, -1, -1):
            key, letter = np.divmod(key, base)
            out[:, j] = letters[letter]
        yield key, _strings(out.reshape(-1), q), n


def _count_wide(texts: list[str], q: int) -> Iterator[tuple[np.ndarray, pa.Array, np.ndarray]]:
    """The same for grams whose number among all of these letters passes 63 bits."""
    for i, t in enumerate(texts):
        found: dict[str, int] = {}
        for k in range(len(t) - q + 1):
            g = t[k : k + q]
            found[g] = found.get(g, 0) + 1
        if found:
            yield np.full(len(found), i), pa.array(list(found), pa.string()), np.fromiter(found.values(), np.int64, len(found))


def qgram_features(rows: DataFrame, q: int) -> DataFrame:
    """(stream_id, gram, cnt) of every q-gram; chunk rows of a stream must overlap by q - 1.

    A row's grams are counted where its text is; only those of streams with several rows meet in a shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, texts, held = [], [], 0
            for i in range(b.num_rows + 1):
                text = b.column(1)[i].as_py() if i < b.num_rows else ""
                if texts and (i == b.num_rows or held + len(text) > TOGETHER):
                    own = pa.array(ids, pa.string())
                    for doc, gram, n in count_grams(texts, q):
                        yield pa.RecordBatch.from_arrays([own.take(pa.array(doc)), gram, pa.array(n, pa.int64())], ["stream_id", "gram", "cnt"])
                    ids, texts, held = [], [], 0
                if i < b.num_rows:
                    ids.append(b.column(0)[i].as_py())
                    texts.append(text)
                    held += len(text)

    rows = rows.where(F.length("text") >= q).select("stream_id", "text")
    several = rows.groupBy("stream_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("stream_id").alias("again"))
    if several.isEmpty():
        return rows.mapInArrow(run, GRAMS)
    same = F.col("stream_id").eqNullSafe(F.col("again"))
    once, more = rows.join(several, same, "left_anti"), rows.join(several, same, "left_semi")
    summed = more.mapInArrow(run, GRAMS).groupBy("stream_id", "gram").agg(F.sum("cnt").alias("cnt"))
    return once.mapInArrow(run, GRAMS).unionByName(summed)


def signature(rows: DataFrame, q: int = 3, bits: int = 4096) -> DataFrame:
    """(stream_id, sig): which q-grams a text may have, in a fixed number of bits."""

    @F.pandas_udf("binary")
    def sign(text: pd.Series) -> pd.Series:
        return text.map(lambda t: gram_signature(t, q, bits))

    return rows.select("stream_id", sign("text").alias("sig"))
