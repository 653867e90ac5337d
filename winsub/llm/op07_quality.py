"""Quality classifier: attention-based multiple-instance learning.

A document is a bag of passages (windows of ``PASSAGE`` bytes over the whole text).  A
passage is described by the frequencies of neighbouring byte classes and by how many words repeat
the word one or two before, and encoded by a hidden layer; gated attention weighs the passages; the weighted sum is classified.  All
weights, attention included, are learned together from document labels.

Fitting reads a sample of labelled documents, whole texts, chosen by a hash: about ``TRAIN_DOCS``
at most, and so many that their texts have about ``TRAIN_BYTES`` bytes at most, of texts of
``LONGEST`` bytes at most; every passage of a sampled document is learned from, and scoring
covers every passage of every document, ``BLOCK`` passages at a time.

Defined results: null text is empty and is one passage without features, so it has a score;
documents without a label are scored; of a document's repeated labels the largest counts, of
repeated labelled rows the least text; ``held_out`` of a null doc_id is false; without labelled rows every score is 0.5; an empty table gives an empty result; columns
other than doc_id and text (and the labels' doc_id and quality) are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.llm.common import fold, lean, slices, spaced, table, utf8, word_hashes

PASSAGE, BLOCK, THRESHOLD = 512, 512, 0.7
TRAIN_DOCS, TRAIN_BYTES, LONGEST = 6000, 32 << 20, 1 << 20
HIDDEN, GATE, EPOCHS, BATCH, RATE = 32, 16, 30, 128, 5e-3

CLASSES = 16
_CLASS = np.full(256, 11, np.int32)
for _k, _bytes in enumerate([b" ", b"\n\r\t", range(97, 123), range(65, 91), range(48, 58), b".", b",", b"!?", b"#$%&*@^~", b"|[]{}<>\\", b"'\"-_"]):
    for _b in _bytes:
        _CLASS[_b] = _k
_CLASS[192:] = 12
_CLASS[128:192] = 13
_CLASS[:9] = 14
for _b in b":;/()=+":
    _CLASS[_b] = 15
FEATURES = CLASSES * CLASSES + 2


def passages(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of every passage of the rows, and each row's first passage."""
    first = _first_passages(offsets)
    return np.concatenate([x for x in _features(data, offsets)]), first


def _first_passages(offsets: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(np.maximum(1, -(-np.diff(offsets) // PASSAGE)))])


def _features(data: np.ndarray, offsets: np.ndarray) -> Iterator[np.ndarray]:
    """Features of the rows' passages in order, about ``BLOCK`` at a time; a long row's in parts."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + BLOCK * PASSAGE, side="right")) - 1)
        own = offsets[at : to + 1]
        size = int(own[-1] - own[0])
        if to - at > 1 or size <= BLOCK * PASSAGE:
            yield _described(data, own)
        else:
            for begin in range(0, size, BLOCK * PASSAGE):
                # A part has the byte before it, and what its last word needs behind it, beside it.
                start, end = own[0] + begin, min(own[1], own[0] + begin + BLOCK * PASSAGE)
                lead = int(begin > 0)
                gap = np.flatnonzero(_CLASS[data[end : min(own[1], end + 256)]] < 2)
                tail = int(gap[0]) if len(gap) else int(min(own[1], end + 256) - end)
                yield _described(data, np.array([start - lead, end + tail]), lead, tail)
        at = to


def _described(data: np.ndarray, offsets: np.ndarray, lead: int = 0, tail: int = 0) -> np.ndarray:
    """Features of whole rows' passages, or of a part of one with ``lead`` and ``tail`` bytes around it."""
    sizes = np.diff(offsets)
    number = np.maximum(1, -(-(sizes - lead - tail) // PASSAGE))
    first = np.concatenate([[0], np.cumsum(number)])
    text, begin = spaced(data, offsets)  # a blank between rows keeps their words apart
    local = np.arange(len(text), dtype=np.int64) - np.repeat(begin[:-1], sizes + 1)
    which = np.repeat(first[:-1], sizes + 1) + np.clip((local - lead) // PASSAGE, 0, np.repeat(number - 1, sizes + 1))
    c = _CLASS[text]
    code = np.zeros(len(c), np.int64)
    code[1:] = c[:-1] * CLASSES
    code[local == 0] = 0
    code += c
    own = np.ones(len(text), bool)
    own[begin[1:] - 1] = False
    own[:lead] = False
    own[len(own) - 1 - tail :] = False
    counts = np.bincount((which * FEATURES + code)[own], minlength=first[-1] * FEATURES).reshape(-1, FEATURES).astype(np.float32)
    x = np.sqrt(counts / np.maximum(1, counts.sum(axis=1, keepdims=True)))
    starts, _, word = word_hashes(text)
    inside = own[starts]
    starts, word = starts[inside], word[inside]
    if len(word) > 1:
        home = which[starts]
        words = np.maximum(1, np.bincount(home, minlength=len(x)))
        for lag in (1, 2):
            again = (word[lag:] == word[:-lag]) & (home[lag:] == home[:-lag])
            x[:, FEATURES - lag] = np.bincount(home[lag:], weights=again, minlength=len(x)) / words
    return x


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Attention:
    """Encoder, gated attention and classifier over bags."""

    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        draw = lambda a, b: (r.normal(size=(a, b)) / np.sqrt(a)).astype(np.float32)
        self.p = {"w": draw(FEATURES, HIDDEN) * 4, "b": np.zeros(HIDDEN, np.float32), "v": draw(HIDDEN, GATE), "u": draw(HIDDEN, GATE), "a": draw(GATE, 1)[:, 0], "c": draw(HIDDEN, 1)[:, 0], "d": np.zeros(1, np.float32)}
        self.fitted = False

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of every passage the hidden layer, both gates and the attention before it is normalised."""
        p = self.p
        h = np.tanh(x @ p["w"] + p["b"])
        t, g = np.tanh(h @ p["v"]), _sigmoid(h @ p["u"])
        return h, t, g, (t * g) @ p["a"]

    def forward(self, x: np.ndarray, first: np.ndarray) -> dict[str, np.ndarray]:
        return self.attend(*self.encode(x), first)

    def attend(self, h: np.ndarray, t: np.ndarray | None, g: np.ndarray | None, e: np.ndarray, first: np.ndarray) -> dict[str, np.ndarray]:
        """The bags' weighted sums and scores."""
        p, at = self.p, first[:-1]
        bag = np.repeat(np.arange(len(at)), np.diff(first))
        e = np.exp(e - np.maximum.reduceat(e, at)[bag])
        weight = e / np.add.reduceat(e, at)[bag]
        z = np.add.reduceat(weight[:, None] * h, at, axis=0)
        return {"bag": bag, "h": h, "t": t, "g": g, "weight": weight, "z": z, "score": _sigmoid(z @ p["c"] + p["d"])}

    def gradient(self, x: np.ndarray, first: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        f, p, at = self.forward(x, first), self.p, first[:-1]
        bag, h, t, g, weight = f["bag"], f["h"], f["t"], f["g"], f["weight"]
        ds = (f["score"] - y) / len(y)
        dz = ds[:, None] * p["c"]
        dweight = (dz[bag] * h).sum(axis=1)
        de = weight * (dweight - np.add.reduceat(weight * dweight, at)[bag])
        dt, dg = de[:, None] * p["a"] * g * (1 - t * t), de[:, None] * p["a"] * t * g * (1 - g)
        dh = (weight[:, None] * dz[bag] + dt @ p["v"].T + dg @ p["u"].T) * (1 - h * h)
        return {"w": x.T @ dh, "b": dh.sum(axis=0), "v": h.T @ dt, "u": h.T @ dg, "a": (t * g).T @ de, "c": f["z"].T @ ds, "d": ds.sum(keepdims=True)}

    def fit(self, x: np.ndarray, first: np.ndarray, y: np.ndarray, seed: int = 11) -> None:
        r, step = np.random.default_rng(seed), 0
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        s = {k: np.zeros_like(v) for k, v in self.p.items()}
        for _ in range(EPOCHS):
            order = r.permutation(len(y))
            for k in range(0, len(y), BATCH):
                some = order[k : k + BATCH]
                sizes = first[some + 1] - first[some]
                starts = np.concatenate([[0], np.cumsum(sizes)])
                rows = np.repeat(first[some] - starts[:-1], sizes) + np.arange(starts[-1])
                step += 1
                for name, d in self.gradient(x[rows].astype(np.float32), starts, y[some]).items():
                    d = d + 1e-5 * self.p[name]
                    m[name] = 0.9 * m[name] + 0.1 * d
                    s[name] = 0.999 * s[name] + 0.001 * d * d
                    self.p[name] = (self.p[name] - RATE * (m[name] / (1 - 0.9**step)) / (np.sqrt(s[name] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        self.fitted = True

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        if not self.fitted:
            return np.full(len(offsets) - 1, 0.5)
        found = [(h, e) for h, _, _, e in map(self.encode, _features(data, offsets))]
        h, e = (np.concatenate(x) for x in zip(*found, strict=True))
        return self.attend(h, None, None, e, _first_passages(offsets))["score"]


def sample(docs: DataFrame, labels: DataFrame, train_docs: int = TRAIN_DOCS, train_bytes: int = TRAIN_BYTES) -> DataFrame:
    """doc_id, text, quality of the labelled documents that fitting reads, one row each."""
    marks = labels.where("quality is not null and doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").cast("int").alias("quality"))
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20))
    some = marks.where(place <= int((1 << 20) * min(1.0, train_docs / max(1, marks.count()))))
    texts = docs.selectExpr("cast(doc_id as long) doc_id", "coalesce(text, '') text").where(F.octet_length("text") <= LONGEST)
    rows = texts.join(F.broadcast(some), "doc_id").groupBy("doc_id", "quality").agg(F.min("text").alias("text"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > train_bytes:
        share = int((1 << 20) * train_bytes / size)
        rows = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(1 << 20)) < share)
    return rows.select("doc_id", "text", "quality")


def fit(docs: DataFrame, labels: DataFrame, train_docs: int = TRAIN_DOCS, train_bytes: int = TRAIN_BYTES) -> Attention:
    """Learn from a hash-chosen sample of the labelled documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, offsets = utf8(b.column(1))
            for i, j in slices(offsets):
                x, first = passages(data, offsets[i : j + 1])
                x = x.astype(np.float16)
                bags = [x[k:e].tobytes() for k, e in zip(first[:-1], first[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(0)[i:j], b.column(2)[i:j], pa.array(bags, pa.binary())], ["doc_id", "quality", "bag"])

    found = sample(docs, labels, train_docs, train_bytes).mapInArrow(lean(run), "doc_id long, quality int, bag binary").toPandas()
    found = found.sort_values("doc_id", kind="stable")
    model = Attention()
    if len(found):
        bags = [np.frombuffer(x, np.float16).reshape(-1, FEATURES) for x in found["bag"]]
        first = np.concatenate([[0], np.cumsum([len(x) for x in bags])])
        model.fit(np.concatenate(bags), first, found["quality"].to_numpy(np.float32))
    return model


def score(docs: DataFrame, model: Attention) -> DataFrame:
    """doc_id, score of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, offsets = utf8(b.column(1))
            for i, j in slices(offsets):
                yield pa.RecordBatch.from_arrays([b.column(0)[i:j], pa.array(model.score(data, offsets[i : j + 1]), pa.float64())], ["doc_id", "score"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run), "doc_id long, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = fit(docs.where(fold("doc_id", 4) != 2), labels.where(fold("doc_id", 4) != 2))
    return score(docs, model).select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def kept_documents(docs: DataFrame, model: Attention, least: float = 0.5) -> DataFrame:
    """The rows that are likelier of good quality than not, all columns."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, offsets = utf8(b.column(at))
            for i, j in slices(offsets):
                yield b.slice(i, j - i).filter(pa.array(model.score(data, offsets[i : j + 1]) >= least, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
