"""Exact token counts of every prefix by dynamic programming, without re-encoding.

Byte-pair encoding has a local test: a sequence of tokens is an encoding if and only if
each neighbouring pair is what encoding the pair's own bytes gives.  So the last token of
every prefix follows from the last tokens of shorter prefixes, and

    count[i] = count[i - len(last[i])] + 1

holds the exact count at every prefix of a pre-token; pre-tokens add up.  ``PrefixCounter``
answers count, truncation and budget questions from that table.  The bulk operator counts
by units that start at a space before a non-space, where pre-tokens always break, and
remembers the units' totals in a bounded table.

Defined results: null text is empty (0 tokens); special strings inside texts are one token
each, as the library's default has it; an empty table gives an empty result; other columns
are not read.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.llm.common import CACHES, lean, table

#: Entries of the remembered tables (words and pairs, units) before they are emptied.
REMEMBERED, UNITS = 300_000, 1_000_000

# The pre-token pattern of the byte-level vocabulary.
PATTERN = regex.compile(
    r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
)
_LONG_SHORTENED = {"'re", "'ve", "'ll"}
_CUT = re.compile(r" (?=\S)")
_BLANK = regex.compile(r"\p{White_Space}+\Z")


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in the vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class PrefixCounter:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        back = lambda s: bytes(letters[c] for c in s)
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.vocab = {back(t): i for t, i in spec["model"]["vocab"].items() if t not in set(self.special)}
        pairs = (m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"])
        self.rank = {(back(a), back(b)): k for k, (a, b) in enumerate(pairs)}
        self.made = {}
        for (a, b), k in self.rank.items():
            self.made.setdefault(a + b, (a, b, k))
        sizes: dict[bytes, set[int]] = {}
        for t in self.vocab:
            if len(t) > 2:
                sizes.setdefault(t[-3:], set()).add(len(t))
        #: Lengths of tokens by their last three bytes, longest first.
        self.sizes = {t: (*sorted(n, reverse=True), 2, 1) for t, n in sizes.items()}
        self.words: dict[str, int] = {}
        self.split_special = re.compile("|".join(map(re.escape, self.special))) if self.special else None
        self.pairs: dict[tuple[bytes, bytes], bool] = {}
        self.units: dict[str, int] = _Units(self)

    def merge(self, word: bytes) -> list[bytes]:
        """Plain byte-pair merging of a short word."""
        parts = [word[i : i + 1] for i in range(len(word))]
        while len(parts) > 1:
            best, at = min((self.rank.get((a, b), 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)))
            if best == 1 << 60:
                break
            a, b = parts[at], parts[at + 1]
            out, i = [], 0
            while i < len(parts):
                if i + 1 < len(parts) and parts[i] == a and parts[i + 1] == b:
                    out.append(a + b)
                    i += 2
                else:
                    out.append(parts[i])
                    i += 1
            parts = out
        return parts

    def _spine(self, token: bytes, side: int) -> list[tuple[bytes, float]]:
        """What stands at one end of a token while it is merged, each with the rank that ends it."""
        spine, ends = [(token, float("inf"))], self.made.get(token)
        while ends is not None:
            a, b, rank = ends
            token = b if side else a
            spine.append((token, rank))
            ends = self.made.get(token)
        return spine

    def fits(self, left: bytes, right: bytes) -> bool:
        """Whether encoding left + right gives just the two: no merge crosses the seam.

        A merge of x (an end of left) and y (a start of right) crosses if its rank comes
        before x is merged further and not after y is; of equal ranks the left goes first.
        """
        key = (left, right)
        known = self.pairs.get(key)
        if known is None:
            if len(self.pairs) >= REMEMBERED:
                self.pairs.clear()
            if left:
                rank, starts = self.rank, self._spine(right, 0)
                known = not any(
                    (k := rank.get((x, y))) is not None and k < until and k <= y_until
                    for x, until in self._spine(left, 1)
                    for y, y_until in starts
                )
            else:
                known = self.merge(right) == [right]
            self.pairs[key] = known
        return known

    def table(self, word: bytes) -> list[int]:
        """count[i]: exact tokens of word[:i], for every byte prefix of one pre-token."""
        n, vocab, sizes, fits, pairs = len(word), self.vocab, self.sizes, self.fits, self.pairs
        last, count = [b""] * (n + 1), [0] * (n + 1)
        for i in range(1, n + 1):
            for size in sizes.get(word[i - 3 : i] if i > 2 else b"", (2, 1)):
                j = i - size
                if j < 0:
                    continue
                token = word[j:i]
                if token in vocab:
                    known = pairs.get((last[j], token))
                    if known if known is not None else fits(last[j], token):
                        last[i], count[i] = token, count[j] + 1
                        break
        return count

    def _letters(self, word: str) -> int:
        """Tokens of a pre-token of letters; remembered."""
        found = self.words.get(word)
        if found is None:
            if len(self.words) >= REMEMBERED:
                self.words.clear()
            found = self.words[word] = self.table(word.encode())[-1]
        return found

    def _plain(self, text: str) -> int:
        return sum(self.table(w.encode())[-1] for w in PATTERN.findall(text))

    def _unit(self, unit: str) -> int:
        """Tokens of " " + unit."""
        if unit.isalpha():
            return self.table(b" " + unit.encode())[-1] if len(unit) < 64 else self._plain(" " + unit)
        if unit[-1] in ".,;:?!" and unit[:-1].isalpha():
            return self._letters(" " + unit[:-1]) + 1
        return self._plain(" " + unit)

    def count(self, text: str) -> int:
        """Tokens of the whole text."""
        if self.split_special and any(s in text for s in self.special):
            parts = self.split_special.split(text)
            return len(parts) - 1 + sum(map(self._segment, parts))
        return self._segment(text)

    def _segment(self, text: str) -> int:
        if not text:
            return 0
        first, *rest = text.split(" ")
        if first:
            try:
                return self._plain(first) + sum(map(self.units.__getitem__, rest))
            except LookupError:
                pass
        first, *rest = _CUT.split(text)
        return self._plain(first) + sum(map(self.units.__getitem__, rest))

    def prefix_counts(self, text: str) -> np.ndarray:
        """Tokens of text[:i] for each i, as encoding each prefix afresh would give."""
        out = np.zeros(len(text) + 1, np.int64)
        at = base = 0
        for m in self.split_special.finditer(text) if self.split_special else ():
            counts = self._plain_prefixes(text[at : m.end() - 1])
            out[at : m.end()] = base + counts
            base += 1 + (self._plain_prefixes(text[at : m.start()])[-1])
            at = m.end()
            out[at] = base
        out[at:] = base + self._plain_prefixes(text[at:])
        return out

    def _plain_prefixes(self, text: str) -> np.ndarray:
        out, base = np.zeros(len(text) + 1, np.int64), 0
        for m in PATTERN.finditer(text):
            word, start = m.group(), m.start()
            counts = self.table(word.encode())
            done = 0
            for k, c in enumerate(word, 1):
                done += len(c.encode())
                out[start + k] = base + counts[done]
            if word in _LONG_SHORTENED:  # cut short it is an apostrophe and a letter
                out[start + 2] = base + 2
            base += counts[-1]
        for m in regex.finditer(r"\p{White_Space}{2,}", text):  # at its end a run is one pre-token
            out[m.end()] = out[m.start()] + self.table(m.group().encode())[-1]
        return out

    def truncate(self, text: str, budget: int) -> str:
        """The longest prefix that needs at most ``budget`` tokens."""
        return text[: int(np.flatnonzero(self.prefix_counts(text) <= budget)[-1])]


class _Units(dict):
    """Tokens of " " + unit; a unit that starts with white space is refused."""

    def __init__(self, counter: PrefixCounter):
        super().__init__()
        self.counter = counter

    def __missing__(self, unit: str) -> int:
        if not unit or unit[0].isspace():
            raise LookupError(unit)
        if len(self) >= UNITS:
            self.clear()
        found = self.counter._unit(unit)
        if len(unit) < 64:
            self[unit] = found
        return found


_COUNTERS: dict[str, PrefixCounter] = CACHES.setdefault("counters", {})


def counter(path: str) -> PrefixCounter:
    if path not in _COUNTERS:
        _COUNTERS[path] = PrefixCounter(path)
    return _COUNTERS[path]


def token_counts(docs: DataFrame, path: str, limit: int = 1024) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(path).count
        for b in batches:
            texts = b.column(1)
            bytes_ = [len(t.as_buffer()) if t.is_valid else 0 for t in texts]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(bytes_, pa.int64()), pa.array([count(t.as_py() or "") for t in texts], pa.int64())],
                ["doc_id", "n_bytes", "n_tokens"],
            )

    rows = docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run, "counters"), "doc_id long, n_bytes long, n_tokens long")
    return rows.withColumn("over_limit", F.col("n_tokens") > limit)


def prefix_tables(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, prefix_tokens: the exact token count of every prefix, by its length in characters (the first is 0)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = counter(path).prefix_counts
        for b in batches:
            for i in range(0, b.num_rows, 64):
                found = [counts(t or "").astype(np.int32) for t in b.column(1)[i : i + 64].to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0)[i : i + 64], pa.array(found, pa.list_(pa.int32()))], ["doc_id", "prefix_tokens"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run, "counters"), "doc_id long, prefix_tokens array<int>")


def longest_within(tables: DataFrame, budget: int) -> DataFrame:
    """doc_id, n_chars, n_tokens: the longest prefix of each text of at most ``budget`` tokens, from its stored table alone."""
    longest = f"array_max(transform(prefix_tokens, (c, i) -> if(c <= {int(budget)}, i, 0)))"
    return tables.select("doc_id", "prefix_tokens", F.expr(longest).alias("n_chars")).select("doc_id", "n_chars", F.expr("prefix_tokens[n_chars]").alias("n_tokens"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
