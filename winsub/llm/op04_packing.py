"""Packing token streams into sequences: minimum bin slack by subset-sum bitsets.

1. Tokenise: every document becomes full windows of ``capacity`` ids and a remainder; the
   pieces' checksums, also those of the remainder's power-of-two parts, are taken here, so
   ids are never stored or shuffled.
2. Plan: only the histogram of remainder lengths (at most ``capacity`` rows, whatever the
   input) reaches the driver.  The longest remaining length opens a window; a bitset
   dynamic programme over the remaining-length multiset finds the sum closest to the room
   left; backtracking gives how many of each length; the pattern is repeated as often as
   the counts allow.  Where the slack exceeds ``tolerance`` half of the largest class that is
   no power of two is cut into its power-of-two parts, which fill later windows; what is left
   in the end, less than a window, goes into a sequence for each bit of its sum.
3. Assign: a remainder's rank inside its length class (a running number inside its input
   partition and a prefix sum over partitions) selects pattern, repetition and offset.

Defined results: null text is empty and has one id, the end id; every id lies in exactly
one piece; a sequence is shorter than the capacity by at most ``tolerance``, or its length
is a power of two; repeated rows are packed like any other; an empty table gives an empty
result; other columns than doc_id and text are not read.
"""

from __future__ import annotations

import os
import struct
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winsub.llm.common import lean, stage, table

CAPACITY, END_ID, TOLERANCE = 4096, 2, 4
#: Words whose ids a worker remembers before it starts afresh.
REMEMBERED = 300_000

CUT_SCHEMA = "doc_id long, doc_tokens long, full_crc array<long>, rem int, rem_crc long, part_crc array<long>, part int, full_rank long, rank long"


#: Packers of few ids: most words are new to a task and short, where an array costs more than its ids.
FEW = [struct.Struct(f"<{n}I").pack for n in range(33)]


def packed(ids: list[int]) -> bytes:
    return FEW[len(ids)](*ids) if len(ids) < len(FEW) else np.array(ids, "<u4").tobytes()


class Words:
    """Ids of words as little-endian 32-bit bytes; tokens never cross ASCII white space.

    The vocabulary is lower case, so words are remembered in lower case (unless a special
    string may stand in the text).  A new word of Latin letters goes to the merging model
    directly, punctuation after it apart; any other word through the whole tokenizer.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.known, self.tails = Tokenizer.from_file(path), {}, {}
        self.model = self.tokenizer.model
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [x for x in range(256) if x not in set(plain)]
        self.letters = {x: chr(x) for x in plain} | {x: chr(256 + k) for k, x in enumerate(rest)}

    def _letters(self, stem: bytes) -> bytes | None:
        """Ids of one run of letters that are not all ASCII, if it is one that needs no normalising."""
        word = stem.decode()
        if not word.isalpha() or max(word) >= "\u0250" or "\u0130" in word or not unicodedata.is_normalized("NFC", word):
            return None
        text = word.lower().encode().decode("latin-1").translate(self.letters)
        return packed([t.id for t in self.model.tokenize(text)])

    def _encode(self, words: list[bytes]) -> list[bytes]:
        found = self.tokenizer.encode_batch_fast([w.decode() for w in words], add_special_tokens=False)
        return [packed(e.ids) for e in found]

    def ids(self, texts: list[bytes]) -> list[bytes]:
        split = [(t if b"<|" in t else t.lower()).split() for t in texts]
        if len(self.known) > REMEMBERED:
            self.known.clear()
        known, tails, odd, tokenize = self.known, self.tails, [], self.model.tokenize
        for w in set().union(*split).difference(known):
            stem = w.rstrip(b".,;:!?")
            found = known.get(stem) if stem[-1:].isalnum() else None
            if found is None and stem and stem == stem.lower():
                found = packed([t.id for t in tokenize(stem.decode())]) if stem.isalpha() else self._letters(stem)
            if found is None:
                odd.append(w)
                continue
            known[stem] = found
            if len(stem) < len(w):
                tail = w[len(stem) :]
                if tail not in tails:
                    if len(tails) > 10_000:
                        tails.clear()
                    tails[tail] = self._encode([tail])[0]
                known[w] = found + tails[tail]
        for i in range(0, len(odd), 4096):
            known.update(zip(odd[i : i + 4096], self._encode(odd[i : i + 4096]), strict=True))
        return [b"".join(map(known.__getitem__, words)) for words in split]


def bits(n: int) -> list[int]:
    """Powers of two that add up to n, largest first."""
    return [1 << k for k in range(n.bit_length() - 1, -1, -1) if n >> k & 1]


def cuts(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Token counts, checksums and ranks of every document's windows and remainder."""
    names = [x.strip().split(" ")[0] for x in CUT_SCHEMA.split(",")]
    longs = pa.list_(pa.int64())
    kinds = [pa.int64(), pa.int64(), longs, pa.int32(), pa.int64(), longs, pa.int32(), pa.int64(), pa.int64()]
    end = struct.pack("<I", end_id)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words(path)  # what it remembers goes with the task
        part, full, seen = TaskContext.get().partitionId(), 0, {}
        for b in batches:
            for i in range(0, b.num_rows, 256):
                rows = []
                ids_of = words.ids([t.as_buffer().to_pybytes() if t.is_valid else b"" for t in b.column(1)[i : i + 256]])
                for doc_id, ids in zip(b.column(0)[i : i + 256].to_pylist(), ids_of, strict=True):
                    ids += end
                    n = len(ids) // 4
                    k, rem = divmod(n, capacity)
                    at, parts = 4 * k * capacity, []
                    view = memoryview(ids)
                    for p in bits(rem):
                        parts.append(zlib.crc32(view[at : at + 4 * p]))
                        at += 4 * p
                    rank = seen.get(rem, 0)
                    rows.append((doc_id, n, [zlib.crc32(view[4 * capacity * j : 4 * capacity * (j + 1)]) for j in range(k)], rem, zlib.crc32(view[4 * k * capacity :]), parts, part, full, rank))
                    full += k
                    seen[rem] = rank + 1
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run), CUT_SCHEMA)


def best_fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of available lengths whose sum is at most ``room`` and closest to it."""
    mask, target = (1 << room + 1) - 1, 1 << room
    reach, steps = 1, []
    for length in sorted((x for x, n in counts.items() if n and x <= room), reverse=True):
        left, chunk = min(counts[length], room // length), 1
        while left:
            take = min(chunk, left)
            steps.append((reach, length, take))
            reach |= reach << length * take & mask
            left -= take
            chunk *= 2
        if reach & target:
            break
    at, fill = reach.bit_length() - 1, {}
    for before, length, take in reversed(steps):
        if not before >> at & 1:
            fill[length] = fill.get(length, 0) + take
            at -= length * take
    return fill


def _dealt(counts: dict[int, int], capacity: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Powers of two into as few sequences as their sum has bits: in falling order they fill one after the other."""
    most, out = 1 << capacity.bit_length() - 1, []
    left = sorted(counts.items(), reverse=True)
    while left:
        size, n = left[0]
        if full := size * n // most:  # so many sequences of the largest power alone
            out.append((full, [(size, most // size)]))
            left[0] = (size, n - full * (most // size))
        else:
            room, fill = 1 << sum(x * k for x, k in left).bit_length() - 1, []
            room = min(room, most)
            for k, (x, have) in enumerate(left):
                take = min(have, room // x)
                if take:
                    fill.append((x, take))
                    left[k], room = (x, have - take), room - x * take
            out.append((1, fill))
        left = [(x, n) for x, n in left if n]
    return out


def plan(histogram: dict[int, int], capacity: int = CAPACITY, tolerance: int = TOLERANCE) -> tuple[list[tuple[int, list[tuple[int, int]]]], dict[int, int]]:
    """Patterns (repetitions, [(length, used), ...]) and how many of each length are cut."""
    counts, cut, patterns = {x: n for x, n in histogram.items() if n and x}, {}, []
    while counts:
        seed = max(counts)
        counts[seed] -= 1
        fill = best_fill(counts, capacity - seed)
        counts[seed] += 1
        slack = capacity - seed - sum(x * n for x, n in fill.items())
        if slack > tolerance:
            odd = max((x for x in counts if len(bits(x)) > 1), default=None)
            if odd is None:  # powers of two alone, too few for a window
                return patterns + _dealt(counts, capacity), cut
            some = -(-counts[odd] // 2)
            cut[odd] = cut.get(odd, 0) + some
            for p in bits(odd):
                counts[p] = counts.get(p, 0) + some
            counts[odd] -= some
        else:
            fill[seed] = fill.get(seed, 0) + 1
            times = min(counts[x] // n for x, n in fill.items())
            patterns.append((times, sorted(fill.items(), reverse=True)))
            for x, n in fill.items():
                counts[x] -= n * times
        counts = {x: n for x, n in counts.items() if n}
    return patterns, cut


class Places:
    """Sequence and offset of the r-th piece of a length, from a plan."""

    def __init__(self, histogram: dict[int, int], patterns: list, cut: dict[int, int]):
        used, rows, sequence = {}, [], 0
        for times, fill in patterns:
            offset = 0
            for length, n in fill:
                rows.append((length, used.get(length, 0), n, sequence, offset))
                used[length] = used.get(length, 0) + n * times
                offset += n * length
            sequence += times
        rows.sort()
        self.sequences = sequence
        table_ = np.array(rows, np.int64).reshape(-1, 5)
        self.length, self.begin, self.n, self.first, self.offset = table_.T
        self.key = self.length << 48 | self.begin
        #: Remainders of these ranks and above are cut; where their parts' ranks begin.
        self.whole = {x: histogram[x] - k for x, k in cut.items()}
        start = dict(histogram)
        self.base = {}
        for x in sorted(cut):
            for p in bits(x):
                self.base[x, p] = start.get(p, 0)
                start[p] = start.get(p, 0) + cut[x]

    def of(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        k = np.searchsorted(self.key, length << 48 | rank, side="right") - 1
        d = rank - self.begin[k]
        return self.first[k] + d // self.n[k], self.offset[k] + d % self.n[k] * length


PIECE_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def _pieces(places: Places, capacity: int):
    names = [x.strip().split(" ")[0] for x in PIECE_SCHEMA.split(",")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []  # doc, start, length, crc, tokens, sequence, rank (of a remainder's piece) or -1
            for doc, tokens, full, rem, crc, parts, first, rank in zip(*(c.to_pylist() for c in b.columns), strict=True):
                for j, c in enumerate(full):
                    out.append((doc, j * capacity, capacity, c, tokens, places.sequences + first + j, -1))
                at = len(full) * capacity
                whole = places.whole.get(rem)
                if not rem:
                    continue
                if whole is None or rank < whole:
                    out.append((doc, at, rem, crc, tokens, 0, rank))
                    continue
                for p, c in zip(bits(rem), parts, strict=True):
                    out.append((doc, at, p, c, tokens, 0, places.base[rem, p] + rank - whole))
                    at += p
            if not out:
                continue
            doc, start, length, crc, tokens, sequence, rank = zip(*out, strict=True)
            length, rank, sequence = np.array(length, np.int64), np.array(rank, np.int64), np.array(sequence, np.int64)
            offset, small = np.zeros(len(rank), np.int64), rank >= 0
            if small.any():
                sequence[small], offset[small] = places.of(length[small], rank[small])
            columns = [pa.array(doc, pa.int64()), start, length, crc, tokens, sequence, offset]
            yield pa.RecordBatch.from_arrays([columns[0], *(pa.array(c, pa.int64()) for c in columns[1:])], names)

    return run


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END_ID, tolerance: int = TOLERANCE) -> DataFrame:
    """One row per piece: where its ids begin in the document, and its sequence and offset."""
    made = stage(cuts(docs, path, capacity, end_id), "cuts")
    classes = made.where("rem > 0").groupBy("part", F.col("rem").alias("class")).agg(F.count(F.lit(1)).alias("n"))
    windows = made.groupBy("part").agg(F.sum(F.size("full_crc")).cast("long").alias("n")).select("part", F.lit(capacity).alias("class"), "n")
    classes = stage(classes.unionByName(windows), "classes")
    histogram = {r["class"]: r["n"] for r in classes.where(F.col("class") < capacity).groupBy("class").agg(F.sum("n").alias("n")).collect()}
    places = Places(histogram, *plan(histogram, capacity, tolerance))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("class").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    before = classes.select("part", "class", before.alias("before"))
    rest = before.where(F.col("class") < capacity).select("part", F.col("class").alias("rem"), F.col("before").alias("rem_before"))
    whole = before.where(F.col("class") == capacity).select("part", F.col("before").alias("full_before"))
    # The classes of all parts grow with the input: they are merged, never broadcast.
    placed = made.join(whole, "part", "left").join(rest.hint("merge"), ["part", "rem"], "left")
    return placed.select(
        "doc_id", "doc_tokens", "full_crc", "rem", "rem_crc", "part_crc",
        (F.col("full_rank") + F.coalesce("full_before", F.lit(0))).alias("full_rank"),
        (F.col("rank") + F.coalesce("rem_before", F.lit(0))).alias("rank"),
    ).mapInArrow(lean(_pieces(places, capacity)), PIECE_SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
