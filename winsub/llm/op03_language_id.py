"""Language ID as multilingual mixture inference.

Each language is a multinomial over hashed character trigrams of words.  A document is a
mixture: expectation-maximisation over its words estimates the language proportions, and
the language set is the prefix of the languages, in order of their proportions, with the
best penalised likelihood (half a logarithm of the word count for each language more).

Fitting reads at most ``TRAIN_DOCS`` documents (expected number; chosen by a hash) of those
with a language and of the training folds, all documents of a language below its share and
so many of each larger one as fill the rest, ``LEAST_DOCS`` of a language in any case; every document is scored over its whole text.

Defined results: null text, or text without a letter, is ``und`` with score 0; ties go to
the first language in order; an empty table gives an empty result; without any training
row every text is ``und``; ``held_out`` of a null doc_id is false; columns other than doc_id, text and lang are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.llm.common import SLICE_BYTES, fold, lean, slices, spaced, table, utf8

#: Expected number of documents that fitting reads, hash buckets, EM rounds.
TRAIN_DOCS, BUCKETS, ROUNDS = 20_000, 1 << 16, 12
#: Documents (expected number) that a language has in fitting, if there are as many.
LEAST_DOCS = 100
#: Words that are handled at one time; words a text has at least before its letters can be those of
#: no language; how far its trigrams are then from usual text (0) towards trigrams never seen (1).
WORDS, STRANGE_WORDS, STRANGE = 1 << 16, 8, 0.75
#: Trigrams of a word overlap: their log-likelihoods are scaled down by this.
TEMPER = 1 / 3

_CLASS = np.full(256, 32, np.uint8)
_CLASS[97:123] = np.arange(97, 123)
_CLASS[65:91] = np.arange(97, 123)
_CLASS[128:] = np.arange(128, 256)
_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[65:91] = _ASCII_LETTER[97:123] = True


def _words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Trigram buckets, the first trigram of each word, the byte where each word begins."""
    c = _CLASS[data].astype(np.uint32)
    framed = np.full(len(c) + 2, 32, np.uint32)
    framed[1:-1] = c
    code = framed[:-2] << 16 | framed[1:-1] << 8 | framed[2:]
    at = np.flatnonzero(c != 32)
    gram = (code[at] * np.uint32(2654435761)) >> np.uint32(16)
    first = np.flatnonzero((code[at] >> 16) == 32)
    return gram, first, at[first]


def _blocks(data: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of about ``limit`` bytes that end where a word ends."""
    at = 0
    while at < len(data):
        to = min(len(data), at + limit)
        while to < len(data) and _CLASS[data[to]] != 32:
            to += 1
        yield at, to
        at = to


class Model:
    def __init__(self, languages: list[str], counts: np.ndarray):
        self.languages = languages
        smooth = counts + 0.05
        log = np.log(smooth / smooth.sum(axis=1, keepdims=True))
        self.logp = (TEMPER * log).T.astype(np.float32).copy()
        if len(languages):
            usual, never = (counts * log).sum() / max(1, counts.sum()), np.log(0.05 / smooth.sum(axis=1)).max()
            self.strange = usual + STRANGE * (never - usual)

    def _likelihoods(self, data: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Languages x words log-likelihoods and each word's row."""
        parts, where = [np.empty((len(self.languages), 0), np.float32)], [np.empty(0, np.int32)]
        for at, to in _blocks(data):
            gram, first, place = _words(data[at:to])
            if len(first):
                parts.append(np.add.reduceat(self.logp[gram], first, axis=0).T)
                where.append((np.searchsorted(begin, place + at, side="right") - 1).astype(np.int32))
        return np.concatenate(parts, axis=1), np.concatenate(where)

    @staticmethod
    def mix(like: np.ndarray, row: np.ndarray, n: int, allowed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Proportions by EM and the log-likelihood of each row's words; ``allowed``, result: languages x rows.

        ``row`` is sorted; words are weighed ``WORDS`` at a time, so memory follows the likelihoods alone.
        """
        share = allowed / allowed.sum(axis=0)
        count = np.maximum(np.bincount(row, minlength=n), 1)
        spans = [slice(at, at + WORDS) for at in range(0, len(row), WORDS)]
        first = [np.flatnonzero(np.diff(row[x], prepend=-1)) for x in spans]
        for _ in range(ROUNDS):
            found = np.zeros_like(share)
            for x, begin in zip(spans, first, strict=True):
                r = share[:, row[x]] * like[:, x]
                r /= r.sum(axis=0)
                found[:, row[x][begin]] += np.add.reduceat(r, begin, axis=1)
            share = found / count
        total = np.zeros(n)
        for x, begin in zip(spans, first, strict=True):
            total[row[x][begin]] += np.add.reduceat(np.log((share[:, row[x]] * like[:, x]).sum(axis=0)), begin)
        return share, total

    def predict(self, data: np.ndarray, offsets: np.ndarray) -> tuple[list[str], list[float], list[list[str]], np.ndarray]:
        """Language, score and language set of every row, and whether its letters are those of no language."""
        n, k = len(offsets) - 1, len(self.languages)
        names, scores, sets, strange = ["und"] * n, [0.0] * n, [[] for _ in range(n)], np.zeros(n, bool)
        if not n or not k:
            return names, scores, sets, strange
        text, begin = spaced(data, offsets)
        like, row = self._likelihoods(text, begin)
        if not len(row):
            return names, scores, sets, strange
        one, peak = np.zeros((k, n)), np.empty(len(row), np.float32)
        for at in range(0, len(row), WORDS):
            part, own = like[:, at : at + WORDS], row[at : at + WORDS]
            peak[at : at + WORDS] = part.max(axis=0)
            np.maximum(part - peak[at : at + WORDS], -30, out=part)
            for j in range(k):
                one[j] += np.bincount(own, weights=part[j], minlength=n)
            np.exp(part, out=part)
        words = np.bincount(row, minlength=n)
        share, full = self.mix(like, row, n, np.ones((k, n)))
        order = np.argsort(-share, axis=0, kind="stable")
        rank = np.argsort(order, axis=0)
        penalty = 0.5 * np.log(np.maximum(words, 2)) + 2.0
        best, chosen = np.full(n, -np.inf), share.copy()
        todo = np.flatnonzero(words)
        for m in range(1, k + 1):
            at = np.searchsorted(todo, row)
            at[at == len(todo)] = 0
            sel = todo[at] == row
            whole = bool(sel.all())
            found, total = self.mix(like if whole else like[:, sel], at if whole else at[sel], len(todo), (rank[:, todo] < m).astype(float))
            value = total - penalty[todo] * (m - 1)
            better = value > best[todo]
            best[todo[better]], chosen[:, todo[better]] = value[better], found[:, better]
            # More languages can gain at most up to the full mixture.
            todo = todo[full[todo] - penalty[todo] * m > best[todo]]
            if not len(todo):
                break
        top = chosen.argmax(axis=0)
        gap = one[top, np.arange(n)] - np.where(np.arange(k)[:, None] == top, -np.inf, one).max(axis=0, initial=-np.inf)
        sure = 1 / (1 + np.exp(-np.clip(gap, -30, 30)))
        # The mixture's log-likelihood of all trigrams.
        mixed = (full + np.bincount(row, weights=peak, minlength=n)) / TEMPER
        strange = (words >= STRANGE_WORDS) & (mixed < self.strange * self._trigrams(text, begin))
        for i in np.flatnonzero(words):
            piece = data[offsets[i] : offsets[i + 1]]
            if not _ASCII_LETTER[piece].any() and not any(ch.isalpha() for ch in piece.tobytes().decode()):
                continue
            names[i], scores[i] = self.languages[top[i]], float(chosen[top[i], i] * max(0.5, sure[i]))
            sets[i] = [self.languages[j] for j in order[:, i] if chosen[j, i] > 0.005]
        return names, scores, sets, strange

    @staticmethod
    def _trigrams(data: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """Number of each row's trigrams, one for each byte of a word."""
        total = np.zeros(len(begin) - 1)
        for at, to in _blocks(data):
            place = np.flatnonzero(_CLASS[data[at:to]] != 32) + at
            total += np.bincount(np.searchsorted(begin, place, side="right") - 1, minlength=len(total))
        return total


def share(sizes: list[int], most: int) -> float:
    """The bound of each size at which the bounded sizes sum to ``most``, ``LEAST_DOCS`` at least."""
    left = float(most)
    for k, n in enumerate(sorted(sizes)):
        even = left / (len(sizes) - k)
        if n > even:
            return max(even, LEAST_DOCS)
        left -= n
    return float(max(sizes))


def fit(docs: DataFrame, train_docs: int = TRAIN_DOCS) -> Model:
    """Trigram counts of each language over a hash-chosen sample of the rows with a language."""
    rows = docs.where("lang is not null and text is not null")
    by = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    languages, total = sorted(by), sum(by.values())
    if not total:
        return Model([], np.zeros((0, BUCKETS)))
    most = share(list(by.values()), train_docs)
    parts = F.create_map(*[F.lit(x) for lang, n in by.items() for x in (lang, int(min(1.0, most / n) * (1 << 20)) + 1)])
    some = rows.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 20)) < parts[F.col("lang")])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((len(languages), BUCKETS), np.int64)
        for b in batches:
            lang = np.array([languages.index(x) for x in b.column(1).to_pylist()])
            data, offsets = utf8(b.column(0))
            for i, j in slices(offsets):
                text, begin = spaced(data, offsets[i : j + 1])
                for at, to in _blocks(text):
                    gram, first, place = _words(text[at:to])
                    if not len(first):
                        continue
                    owner = lang[i + np.searchsorted(begin, place + at, side="right") - 1]
                    owner = np.repeat(owner, np.diff(np.append(first, len(gram))))
                    np.add.at(counts, (owner, gram), 1)
        k, bucket = np.nonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(bucket, pa.int64()), pa.array(counts[k, bucket], pa.int64())], ["k", "bucket", "n"])

    found = some.select("text", "lang").mapInArrow(lean(count), "k long, bucket long, n long").groupBy("k", "bucket").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros((len(languages), BUCKETS))
    counts[found["k"].to_numpy(np.int64), found["bucket"].to_numpy(np.int64)] = found["n"].to_numpy(float)
    return Model(languages, counts)


PREDICTED = "doc_id long, lang_pred string, score double, languages array<string>"


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score, languages (the chosen set) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, offsets = utf8(b.column(1))
            for i, j in slices(offsets):
                names, scores, sets, _ = model.predict(data, offsets[i : j + 1])
                yield pa.RecordBatch.from_arrays([b.column(0)[i:j], pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(sets, pa.list_(pa.string()))], ["doc_id", "lang_pred", "score", "languages"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run), PREDICTED)


def training_rows(docs: DataFrame) -> DataFrame:
    return docs.where(fold("doc_id", 4) != 2)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = predict(docs, fit(training_rows(docs)))
    return found.select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score", "languages")


def kept_documents(docs: DataFrame, model: Model) -> DataFrame:
    """The rows whose language can be told, all columns.

    Texts without a letter go, and texts of some words of which the mixture of all languages finds
    most trigrams as unlikely as any never seen; without a model all with a letter stay.
    """
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, offsets = utf8(b.column(at))
            for i, j in slices(offsets):
                if model.languages:
                    names, _, _, strange = model.predict(data, offsets[i : j + 1])
                    keep = np.array([x != "und" for x in names], bool) & ~strange
                else:
                    keep = np.array([any(ch.isalpha() for ch in t or "") for t in b.column(at)[i:j].to_pylist()], bool)
                yield b.slice(i, j - i).filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
