"""LM scoring by context-tree weighting, beside a word-frequency base score.

A text is its UTF-8 bytes and one end symbol (255, which UTF-8 does not use), each coded as
eight binary decisions.  For every decision the contexts of 0 to ``DEPTH`` preceding bytes form
a tree; each node has a Krichevsky-Trofimov estimate from the training counts, and the
weighting mixes the node's own estimate with its children's, bottom up, by their exact
evidence.  The score is log10 of the probability of the text and its end; code length per byte
follows from it.

Counts cover the whole training text, and the tree has every context counted.  A *path* is a
symbol below its context, the latest byte highest, so paths in order are the tree's leaves in
depth-first order.  Paths are dealt out by their two latest bytes and sorted; a task weighs
the subtrees of three bytes one after the other and hands the two-byte nodes on, whose
evidences Spark sums.  Nodes of one byte and none (65,536 at most) are weighed on the driver.
The mixture comes down the same way: a task meets its two-byte nodes before their paths.

Log probabilities of the paths above a count chosen so that at most ``CODES`` exceed it are
sent to the workers, where scoring is one lookup a byte; all other paths of a text are asked of
the tree in one more pass, in which what was never counted has no counts and so takes the
mixture of its longest counted suffix.  Words are counted by 64-bit hashes; their counts grow
with the input and stay distributed; only words above a count chosen so that at most ``HEAVY``
exceed it are sent to the workers, all others meet their counts in a join.

Defined results: null text is empty: one token and one symbol (the end); without training
rows N is 0, V is 1 (the end), nothing is known and every decision is even; ``held_out`` of a
null doc_id is false; rows with one doc_id are scored each; an empty table gives an empty
result; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.llm.common import blocks, fold, lean, slices, spaced, stage, table, utf8, word_hashes

#: Bytes of context (3 to 6: paths are longs); the end of a text.
DEPTH, END = 4, 255
#: Words and paths at most that workers hold; distinct ones a worker gathers before it hands them on.
HEAVY, CODES, GATHER = 1 << 20, 1 << 20, 1 << 20
#: Symbols handled at one time; paths weighed at one time (and those of one three-byte context).
BLOCK, WEIGHED = 1 << 17, 1 << 15
LN2 = math.log(2)


def paths(text: np.ndarray, begin: np.ndarray, at: int, to: int) -> np.ndarray:
    """The path of each symbol of text[at:to]; rows start at ``begin``, before them stand zeros."""
    out = text[at:to].astype(np.int64)
    near = begin[np.searchsorted(begin, at - DEPTH) : np.searchsorted(begin, to)] - at
    for k in range(1, DEPTH + 1):
        back = np.zeros(to - at, np.int64)
        lead = max(0, k - at)
        back[lead:] = text[at + lead - k : to - k]
        for j in range(k):
            cut = near + j
            back[cut[(cut >= 0) & (cut < to - at)]] = 0
        out |= back << 8 * (DEPTH + 1 - k)
    return out


def _log_kt(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Log evidence of a zeros and b ones under the Krichevsky-Trofimov estimate."""
    return _lgamma(a + 0.5) + _lgamma(b + 0.5) - 2 * math.lgamma(0.5) - _lgamma(a + b + 1.0)


def _lgamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after shifting small arguments."""
    y = np.array(x, np.float64)
    shift = np.zeros_like(y)
    for _ in range(8):
        small = y < 8
        if not small.any():
            break
        shift[small] += np.log(y[small])
        y[small] += 1
    z = 1 / (y * y)
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + (1 / 12 - z * (1 / 360 - z * (1 / 1260 - z / 1680))) / y - shift


def above(key):
    """The node of the same decision one context byte shorter; works on arrays and columns."""
    if isinstance(key, Column):
        return F.shiftleft(F.shiftright(key, 16), 8) + key.bitwiseAND(F.lit(255))
    return key >> 16 << 8 | key & 255


class Level:
    """Nodes of one depth, sorted by key (context << 8 | decision), weighed."""

    def __init__(self, key: np.ndarray, zeros: np.ndarray, ones: np.ndarray, below: np.ndarray | None = None):
        self.key, self.zeros, self.ones = key, zeros, ones
        evidence = _log_kt(zeros, ones)
        self.own = (ones + 0.5) / (zeros + ones + 1)
        if below is None:
            self.whole, self.stop = evidence, np.ones(len(key))
        else:
            self.whole = np.logaddexp(evidence, below) - LN2
            self.stop = np.exp(evidence - LN2 - self.whole)

    def shorter(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Keys one byte shorter, and sums of zeros, ones and evidence over their longer contexts."""
        key, where = np.unique(above(self.key), return_inverse=True)
        return key, *(np.bincount(where, weights=x, minlength=len(key)) for x in (self.zeros, self.ones, self.whole))

    def come_down(self, gone: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What contexts down to these nodes give to a one, and the weight left, from the parents' ones."""
        return gone + left * self.stop * self.own, left * (1 - self.stop)


def leaves(path: np.ndarray, n: np.ndarray) -> Level:
    """The longest contexts' nodes of sorted distinct paths with counts."""
    keys, zeros, ones = [np.empty(0, np.int64)], [np.empty(0)], [np.empty(0)]
    for k in range(8 if len(path) else 0):
        place = path >> 8 - k
        first = np.flatnonzero(np.diff(place, prepend=place[0] - 1))
        bit = path >> 7 - k & 1
        one = np.add.reduceat(n * bit, first).astype(float)
        keys.append(path[first] >> 8 << 8 | 1 << k | (path[first] & 255) >> 8 - k)
        ones.append(one)
        zeros.append(np.add.reduceat(n, first) - one)
    key = np.concatenate(keys)
    order = np.argsort(key)
    return Level(key[order], np.concatenate(zeros)[order], np.concatenate(ones)[order])


def subtrees(path: np.ndarray, n: np.ndarray) -> list[Level]:
    """Levels of three bytes to ``DEPTH`` of whole three-byte contexts."""
    levels = [leaves(path, n)]
    for _ in range(DEPTH - 3):
        levels.insert(0, Level(*levels[0].shorter()))
    return levels


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns of sorted rows (two, path, ...) in runs of about ``WEIGHED`` that end with a three-byte context."""
    held: list[np.ndarray] | None = None
    for b in batches:
        new = [c.to_numpy(zero_copy_only=False) for c in b.columns]
        held = new if held is None else [np.concatenate(x) for x in zip(held, new, strict=True)]
        if len(held[0]) >= WEIGHED:
            three = np.where(held[1] < 0, held[0] << 8, held[1] >> 8 * (DEPTH - 2))
            cut = int(np.searchsorted(three, three[-1]))
            if cut:
                yield [x[:cut] for x in held]
                held = [x[cut:] for x in held]
    if held is not None and len(held[0]):
        yield held


TWO = "key long, zeros double, ones double, below double"


def _up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted (two, path, n) -> the part that whole three-byte contexts give to two-byte nodes."""
    for _, path, n in _runs(batches):
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in subtrees(path, n)[0].shorter()], ["key", "zeros", "ones", "below"])


def _weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        x = Level(*(c.to_numpy() for c in b.columns))
        yield pa.RecordBatch.from_arrays([*b.columns[:3], *(pa.array(y) for y in (x.whole, x.stop, x.own))], ["key", "zeros", "ones", "whole", "stop", "own"])


def _down(gone: np.ndarray, left: np.ndarray):
    """``gone``, ``left``: of every one-byte node, by key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = (np.empty(0, np.int64), np.empty(0), np.empty(0))
        for two, path, n, asked, stop, own in _runs(batches):
            node = path < 0
            key = two[node] << 8 | path[node] + 256
            up, s = above(key), stop[node]
            rows = (key, gone[up] + left[up] * s * own[node], left[up] * (1 - s))
            nodes = [np.concatenate(x) for x in zip(held, rows, strict=True)]
            last = nodes[0] >> 8 == two[-1]
            held = tuple(x[last] for x in nodes)
            path, n, asked = path[~node], n[~node], asked[~node]
            if not len(path):
                continue
            first = np.flatnonzero(np.diff(path, prepend=path[0] - 1))
            path, n, asked = path[first], np.add.reduceat(n, first), np.maximum.reduceat(asked, first)
            if not asked.any():
                continue
            levels = subtrees(path, n)
            # Of a two-byte node that was never counted the estimate is even and half the weight stays.
            up = above(levels[0].key)
            at = np.minimum(np.searchsorted(nodes[0], up), max(0, len(nodes[0]) - 1))
            there = nodes[0][at] == up if len(nodes[0]) else np.zeros(len(up), bool)
            g, w = gone[above(up)] + left[above(up)] / 4, left[above(up)] / 2
            g[there], w[there] = nodes[1][at[there]], nodes[2][at[there]]
            for k, level in enumerate(levels):
                if k:
                    at = np.searchsorted(levels[k - 1].key, above(level.key))
                    g, w = g[at], w[at]
                g, w = level.come_down(g, w)
            some = asked > 0
            path, log = path[some], np.zeros(int(some.sum()))
            for k in range(8):
                p = g[np.searchsorted(levels[-1].key, path >> 8 << 8 | 1 << k | (path & 255) >> 8 - k)]
                log += np.log10(np.where(path >> 7 - k & 1 == 1, p, 1 - p))
            yield pa.RecordBatch.from_arrays([pa.array(path), pa.array(n[some]), pa.array(log)], ["path", "n", "log"])

    return lean(run)


class ContextTree:
    """Frozen mixture over all counted contexts: counted paths, two-byte nodes, what comes from above."""

    def __init__(self, grams: DataFrame):
        self.grams = grams
        two = self._dealt(grams.select(_two(), "path", "n")).mapInArrow(lean(_up), TWO)
        two = two.groupBy("key").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("below").alias("below"))
        self.two = stage(two.mapInArrow(lean(_weigh), "key long, zeros double, ones double, whole double, stop double, own double"), "two")
        one = self.two.groupBy(above(F.col("key")).alias("key")).agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("whole").alias("below")).toPandas()  # at most 65,536 rows
        dense = np.zeros((3, 1 << 16))
        dense[:, one["key"].to_numpy(np.int64)] = one[["zeros", "ones", "below"]].to_numpy(float).T
        level = Level(np.arange(1 << 16), *dense)
        _, zeros, ones, whole = level.shorter()
        gone, left = Level(np.arange(256), zeros, ones, whole).come_down(np.zeros(256), np.ones(256))
        self.gone, self.left = level.come_down(np.tile(gone, 256), np.tile(left, 256))

    @staticmethod
    def _dealt(rows: DataFrame) -> DataFrame:
        return rows.repartition("two").sortWithinPartitions("two", "path")

    def logs(self, rows: DataFrame) -> DataFrame:
        """(path, n, asked: 0 or 1), counted paths all among them -> (path, n, log10) of the asked ones."""
        rows = rows.select(_two(), "path", "n", F.col("asked").cast("long").alias("asked"), F.lit(0.0).alias("stop"), F.lit(0.0).alias("own"))
        nodes = self.two.select(F.shiftright("key", 8).alias("two"), (F.col("key").bitwiseAND(F.lit(255)) - 256).alias("path"), F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("asked"), "stop", "own")
        return self._dealt(rows.unionByName(nodes)).mapInArrow(_down(self.gone, self.left), "path long, n long, log double")


def _two() -> Column:
    return F.shiftright("path", 8 * (DEPTH - 1)).alias("two")


class Known:
    """Paths and their log10 probabilities: one table of a tag and a float each; what collides is searched for."""

    def __init__(self, path: np.ndarray, n: np.ndarray, log: np.ndarray):
        order = np.argsort(path)
        self.path, self.n, self.log = path[order], n[order].astype(np.float32), log[order].astype(np.float32)
        self._fill()

    def _fill(self) -> None:
        self.bits = 8 * (DEPTH + 1)
        self.rest = max(0, min(31, self.bits - 4, self.bits - (2 * len(self.path)).bit_length()))
        self.table = np.zeros(1 << self.bits - self.rest, np.uint64)
        order = np.argsort(self.n, kind="stable")  # of paths that collide the most frequent stays
        slot, tag = self._place(self.path[order])
        self.table[slot] = tag | self.log[order].view(np.uint32)

    def __getstate__(self):
        return self.path, self.n, self.log

    def __setstate__(self, state):
        self.path, self.n, self.log = state
        self._fill()

    def _place(self, path: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Slot, and a tag that with the slot determines the path: an odd factor is one-to-one."""
        mixed = path.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) & np.uint64((1 << self.bits) - 1)
        return (mixed >> np.uint64(self.rest)).astype(np.int64), ((mixed & np.uint64((1 << self.rest) - 1)) + np.uint64(1)) << np.uint64(32)

    def find(self, path: np.ndarray) -> np.ndarray:
        """Logs of the paths, NaN for those not held."""
        slot, tag = self._place(path)
        held = self.table[slot]
        out = held.astype(np.uint32).view(np.float32)
        other = np.flatnonzero(held >> np.uint64(32) << np.uint64(32) != tag)
        out[other] = np.nan
        if len(self.path) and len(other):
            left = path[other]
            at = np.minimum(np.searchsorted(self.path, left), len(self.path) - 1)
            there = self.path[at] == left
            out[other[there]] = self.log[at[there]]
        return out


class Words:
    """Counts of word hashes in an open table; what collides is searched for."""

    def __init__(self, word: np.ndarray, n: np.ndarray):
        order = np.argsort(word)
        self.word, self.n = word[order], n[order]
        self._fill()

    def _fill(self) -> None:
        self.shift = np.uint64(64 - max(4, (2 * len(self.word)).bit_length()))
        self.table = np.zeros(1 << 64 - int(self.shift), np.int32)
        order = np.argsort(self.n, kind="stable")
        self.table[(self.word[order].view(np.uint64) >> self.shift).astype(np.int64)] = order
        self.log = np.log10(self.n + 0.5)

    def __getstate__(self):
        return self.word, self.n

    def __setstate__(self, state):
        self.word, self.n = state
        self._fill()

    def find(self, word: np.ndarray) -> np.ndarray:
        """Places of the words, -1 for those not held."""
        if not len(self.word):
            return np.full(len(word), -1)
        at = self.table[(word.view(np.uint64) >> self.shift).astype(np.int64)].astype(np.int64)
        other = np.flatnonzero(self.word[at] != word)
        left = np.minimum(np.searchsorted(self.word, word[other]), len(self.word) - 1)
        at[other] = np.where(self.word[left] == word[other], left, -1)
        return at


class Gathered:
    """Counts of longs, merged now and then so that memory follows the distinct ones."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.size = self.merged = 0

    def add(self, values: np.ndarray) -> bool:
        """True when there are so many that they should be handed on."""
        self.parts.append(np.unique(values, return_counts=True))
        self.size += len(self.parts[-1][0])
        if self.size > self.merged + GATHER // 2:
            self.merge()
        return self.merged > GATHER

    def merge(self) -> tuple[np.ndarray, np.ndarray]:
        values = np.concatenate([c for c, _ in self.parts] or [np.empty(0, np.int64)])
        found, where = np.unique(values, return_inverse=True)
        total = np.bincount(where, weights=np.concatenate([n for _, n in self.parts] or [np.empty(0)]), minlength=len(found)).astype(np.int64)
        self.parts, self.size, self.merged = [(found, total)], len(found), len(found)
        return found, total


def _ended(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The rows' bytes each with an end, the same with blanks for ends, and where rows begin."""
    words, begin = spaced(data, offsets)
    text = words.copy()
    text[begin[1:] - 1] = END
    return text, words, begin


COUNTED = "word long, path long, n long"


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of words, of paths, and of texts (word and path null)."""
    words, grams, texts = Gathered(), Gathered(), 0

    def given(found: Gathered, column: int) -> Iterator[pa.RecordBatch]:
        values, n = found.merge()
        found.__init__()
        for k in range(0, len(values), 1 << 16):
            part = [pa.nulls(len(values[k : k + (1 << 16)]), pa.int64())] * 2 + [pa.array(n[k : k + (1 << 16)])]
            part[column] = pa.array(values[k : k + (1 << 16)])
            yield pa.RecordBatch.from_arrays(part, ["word", "path", "n"])

    for b in batches:
        data, offsets = utf8(b.column(0))
        texts += b.num_rows
        for i, j in slices(offsets):
            text, plain, begin = _ended(data, offsets[i : j + 1])
            for at in range(0, len(text), BLOCK):
                if grams.add(paths(text, begin, at, min(len(text), at + BLOCK))):
                    yield from given(grams, 1)
            for at, to in blocks(plain):
                if words.add(word_hashes(plain[at:to])[2].view(np.int64)):
                    yield from given(words, 0)
    yield from given(words, 0)
    yield from given(grams, 1)
    yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([texts], pa.int64())], ["word", "path", "n"])


class Model:
    """Word counts (distributed), their totals, the frequent words, the context tree and its frequent paths."""

    def __init__(self, words: DataFrame, total: int, distinct: int, end: int, heavy: Words, tree: ContextTree, known: Known):
        self.words, self.total, self.distinct, self.end, self.heavy, self.tree, self.known = words, total, distinct, end, heavy, tree, known


def least_count(rows: DataFrame, most: int) -> tuple[int | None, list[tuple[int, int, int]]]:
    """The smallest power of two that at most ``most`` rows' n reach; rows and sum by power."""
    by = rows.groupBy(F.floor(F.log2("n")).cast("int").alias("b")).agg(F.count(F.lit(1)).alias("w"), F.sum("n").alias("t"))
    by = sorted(((r["b"], r["w"], r["t"]) for r in by.collect()), reverse=True)
    least, held = None, 0
    for b, w, _ in by:
        if held + w > most:
            break
        least, held = 1 << b, held + w
    return least, by


def fit(docs: DataFrame, heavy: int = HEAVY, codes: int = CODES) -> Model:
    """Counts over every training row; workers get at most ``heavy`` words and ``codes`` paths."""
    found = stage(docs.select("text").mapInArrow(lean(_counts), COUNTED), "counts")
    end = found.where("word is null and path is null").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]
    words = stage(found.where("word is not null").groupBy("word").agg(F.sum("n").alias("n")), "words")
    least, by = least_count(words, heavy)
    often = words.where(F.col("n") >= (least or 1 << 62)).toArrow()
    grams = stage(found.where("path is not null").groupBy("path").agg(F.sum("n").alias("n")), "grams")
    tree = ContextTree(grams)
    least_path, _ = least_count(grams, codes)
    known = tree.logs(grams.select("path", "n", (F.col("n") >= (least_path or 1 << 62)).alias("asked"))).toArrow()
    column = lambda t, name: t[name].to_numpy()
    return Model(words, sum(t for _, _, t in by) + end, sum(w for _, w, _ in by) + 1, end, Words(column(often, "word"), column(often, "n")), tree, Known(*(column(known, x) for x in ("path", "n", "log"))))


SCORED = "row long, doc_id long, n_tokens long, n_known long, log_sum double, score double, n_bytes long, word long, path long"
_NAMES = [x.split(" ")[0] for x in SCORED.split(", ")]


def _rows(row: np.ndarray, **columns: np.ndarray | pa.Array) -> Iterator[pa.RecordBatch]:
    kinds = {"log_sum": pa.float64(), "score": pa.float64()}
    for k in range(0, len(row), 1 << 16):
        part = {x: pa.array(c[k : k + (1 << 16)]) if isinstance(c, np.ndarray) else c[k : k + (1 << 16)] for x, c in ({"row": row} | columns).items()}
        yield pa.RecordBatch.from_arrays([part[x] if x in part else pa.nulls(len(part["row"]), kinds.get(x, pa.int64())) for x in _NAMES], _NAMES)


def _score(sent, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heavy, known = sent.value
        end_log, at_row = math.log10(end + 0.5), TaskContext.get().partitionId() << 33
        for b in batches:
            data, offsets = utf8(b.column(1))
            for i, j in slices(offsets):
                n, row = j - i, at_row + np.arange(j - i)
                text, plain, begin = _ended(data, offsets[i : j + 1])
                score, log_sum, tokens, held = np.zeros(n), np.full(n, end_log), np.ones(n, np.int64), np.full(n, int(end > 0))
                for at in range(0, len(text), BLOCK):
                    to = min(len(text), at + BLOCK)
                    path = paths(text, begin, at, to)
                    log = known.find(path)
                    missed = np.flatnonzero(np.isnan(log))
                    log[missed] = 0
                    edge = np.clip(begin, at, to) - at
                    total = np.concatenate([[0.0], np.cumsum(log, dtype=np.float64)])
                    score += total[edge[1:]] - total[edge[:-1]]
                    yield from _rows(row[np.searchsorted(begin, at + missed, side="right") - 1], path=path[missed])
                for at, to in blocks(plain):
                    starts, _, word = word_hashes(plain[at:to])
                    owner, word = np.searchsorted(begin, starts + at, side="right") - 1, word.view(np.int64)
                    place = heavy.find(word)
                    hit = place >= 0
                    tokens += np.bincount(owner, minlength=n)
                    held += np.bincount(owner[hit], minlength=n)
                    log_sum += np.bincount(owner[hit], weights=heavy.log[place[hit]], minlength=n)
                    yield from _rows(row[owner[~hit]], word=word[~hit])
                yield from _rows(row, doc_id=b.column(0)[i:j], n_tokens=tokens, n_known=held, log_sum=log_sum, score=score, n_bytes=np.diff(offsets[i : j + 1]))
                at_row += n

    return lean(run)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte of every row."""
    sent = docs.sparkSession.sparkContext.broadcast((model.heavy, model.known))  # at most HEAVY words and CODES paths
    rows = stage(docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(_score(sent, model.end), SCORED), "scored")
    zero = F.lit(0).cast("long")
    met = rows.where("word is not null").select("row", "word").join(model.words, "word", "left")
    met = met.select("row", F.log10(F.coalesce("n", zero) + 0.5).alias("log_sum"), (F.col("n") > 0).cast("long").alias("n_known"), F.lit(0.0).alias("score"))
    missed = rows.where("path is not null").select("row", "path")
    asked = missed.select("path").distinct().select("path", zero.alias("n"), F.lit(1).alias("asked"))
    logs = model.tree.logs(model.tree.grams.select("path", "n", F.lit(0).alias("asked")).unionByName(asked)).select("path", "log")
    missed = missed.join(logs, "path").select("row", F.lit(0.0).alias("log_sum"), zero.alias("n_known"), F.col("log").alias("score"))
    main = rows.where("word is null and path is null")
    extra = met.unionByName(missed).groupBy("row").agg(*(F.sum(x).alias(f"more_{x}") for x in ("log_sum", "n_known", "score")))
    whole = {x: F.col(x) + F.coalesce(f"more_{x}", zero) for x in ("log_sum", "n_known", "score")}
    scored = main.join(extra, "row", "left").withColumns(whole)
    return scored.select(
        "doc_id",
        "n_tokens",
        "n_known",
        F.lit(model.total).cast("long").alias("train_tokens"),
        (F.col("log_sum") - F.col("n_tokens") * math.log10(model.total + 0.5 * (model.distinct + 1))).alias("base_score"),
        "score",
        (-F.col("score") * math.log2(10) / F.greatest("n_bytes", F.lit(1))).alias("bits_per_byte"),
    )


def held_out() -> Column:
    return F.coalesce(fold("doc_id", 5) == 1, F.lit(False))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = score(docs, fit(docs.where(~held_out())))
    return found.select("doc_id", held_out().alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte")
