"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie.

Pieces and log scores come from a ``.model`` file.  A file of merges has ranks for scores; the
log score of rank r is then that of Zipf's law, -log(r + 1) less the logarithm of the law's
sum, so few pieces beat many (``scores="ranks"`` sums the ranks as they stand).  Text is marked
(a leading marker, each space becomes the marker) and segmented to the piece sequence of the
highest total score; characters that no piece covers fall back to byte pieces.  Where no piece
has a marker after another character, the best path breaks before every marker run that
follows a character, so segments are solved apart and remembered in a bounded table; otherwise
the whole text is one segment.  Scores are summed as exact doubles; of a segment only the
scores a piece's length back and four bytes a byte of text are held.

Defined results: null text is empty and gives no piece; ties go to the longest last piece;
decoding restores the text exactly, except that a marker character inside a text becomes a
space; repeated rows are coded each; an empty table gives an empty result; other columns are
not read.
"""

from __future__ import annotations

import hashlib
import math
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from winsub.llm.common import CACHES, lean, table

MARK = "▁"
REMEMBERED = 400_000
#: Added to the lowest score for a character without a piece.
UNKNOWN_PENALTY = -10.0
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # fixed values: piece types


UNIGRAM, MERGES = 1, 2  # fixed values: kinds of model


def read_pieces(path: str, scores: str = "log") -> list[tuple[str, float, int]]:
    """(piece, score, type) in order of ids, from the model file's wire format."""
    with open(path, "rb") as f:
        data = f.read()

    def varint(at: int) -> tuple[int, int]:
        shift = value = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            shift += 7
            if b < 128:
                return value, at

    def fields(at: int, end: int):
        while at < end:
            key, at = varint(at)
            kind = key & 7
            if kind == 0:
                value, at = varint(at)
            elif kind == 2:
                size, at = varint(at)
                value, at = (at, at + size), at + size
            else:
                value, at = data[at : at + (4 if kind == 5 else 8)], at + (4 if kind == 5 else 8)
            yield key >> 3, value

    out, model = [], UNIGRAM
    for number, value in fields(0, len(data)):
        if number == 2:
            model = next((v for n, v in fields(*value) if n == 3), UNIGRAM)
        elif number == 1:
            piece, score, kind = "", 0.0, NORMAL
            for n, v in fields(*value):
                if n == 1:
                    piece = data[v[0] : v[1]].decode()
                elif n == 2:
                    score = float(np.frombuffer(v, "<f4")[0])
                elif n == 3:
                    kind = v
            out.append((piece, score, kind))
    return zipf(out) if model == MERGES and scores == "log" else out


def zipf(pieces: list[tuple[str, float, int]]) -> list[tuple[str, float, int]]:
    """Ranks, the best 0 and others below, to log scores; of every kind but normal pieces they stay."""
    order = sorted((i for i, p in enumerate(pieces) if p[2] in (NORMAL, USER)), key=lambda i: -pieces[i][1])
    total, out = math.log(math.fsum(1 / r for r in range(1, len(order) + 1))), list(pieces)
    for r, i in enumerate(order, 1):
        out[i] = (pieces[i][0], -math.log(r) - total, pieces[i][2])
    return out


class DoubleArray:
    """Keys of bytes in two integer arrays: child of s by byte b is base[s] + b + 1 if check says so."""

    def __init__(self, keys: list[bytes]):
        order = sorted(range(len(keys)), key=keys.__getitem__)
        self.base, self.check, self.value = array("i", [0]), array("i", [-1]), array("i", [-1])
        stack = [(0, 0, len(order), 0)]
        while stack:
            node, lo, hi, depth = stack.pop()
            if len(keys[order[lo]]) == depth:
                self.value[node] = order[lo]
                lo += 1
            groups: list[tuple[int, int, int]] = []
            for i in range(lo, hi):
                b = keys[order[i]][depth]
                if groups and groups[-1][0] == b:
                    groups[-1] = (b, groups[-1][1], i + 1)
                else:
                    groups.append((b, i, i + 1))
            if not groups:
                continue
            at = max(0, len(self.check) - 128)  # holes further back are left: the search stays short
            while any((s := at + b + 1) < len(self.check) and self.check[s] >= 0 for b, _, _ in groups):
                at += 1
            need = at + groups[-1][0] + 2 - len(self.check)
            if need > 0:
                self.base.extend([0] * need)
                self.check.extend([-1] * need)
                self.value.extend([-1] * need)
            self.base[node] = at
            for b, i, j in groups:
                self.check[at + b + 1] = node
                stack.append((at + b + 1, i, j, depth + 1))
        self.base.extend([0] * 257)
        self.check.extend([-1] * 257)

    def prefixes(self, text: bytes, at: int) -> Iterator[tuple[int, int]]:
        """(end, key number) of every key that text has at ``at``."""
        base, check, value, node = self.base, self.check, self.value, 0
        for i in range(at, len(text)):
            child = base[node] + text[i] + 1
            if check[child] != node:
                return
            node = child
            if value[node] >= 0:
                yield i + 1, value[node]


class Pieces:
    def __init__(self, path: str, scores: str = "log"):
        pieces = read_pieces(path, scores)
        usable = [i for i, (_, _, kind) in enumerate(pieces) if kind in (NORMAL, USER)]
        self.ids = usable
        self.score = [pieces[i][1] for i in usable]
        keys = [pieces[i][0].encode() for i in usable]
        self.trie, self.size = DoubleArray(keys), [len(k) for k in keys]
        self.ring = 1 << max(4, *self.size).bit_length()
        self.unknown = min(self.score) + UNKNOWN_PENALTY
        self.bytes = {int(p[1:-1], 16): i for i, (p, _, kind) in enumerate(pieces) if kind == BYTE}
        self.unk = next((i for i, p in enumerate(pieces) if p[2] == UNKNOWN), 0)
        self.text = [b"" if kind == CONTROL else bytes([int(p[1:-1], 16)]) if kind == BYTE else p.encode() for p, _, kind in pieces]
        self.breaks = not any(MARK in p.lstrip(MARK) for p, _, kind in pieces if kind in (NORMAL, USER))
        self.known = _Segments(self)

    def segment(self, marked: str) -> array:
        """Viterbi over the trie: ids of the best segmentation of marked text."""
        text = marked.encode()
        n = len(text)
        # best: a ring of the scores that a piece from here can reach; come: the last piece, -1 a bare character.
        mask, low = self.ring - 1, -math.inf
        best, come = [low] * self.ring, array("i", [0]) * (n + 1)
        best[0] = 0.0
        base, check, value, score, unknown = self.trie.base, self.trie.check, self.trie.value, self.score, self.unknown
        at = 0
        while at < n:
            first = text[at]
            width = 1 if first < 128 else 2 if first < 224 else 3 if first < 240 else 4
            here, node, single = best[at & mask], 0, False
            best[at & mask] = low
            for i in range(at, n):
                child = base[node] + text[i] + 1
                if check[child] != node:
                    break
                node = child
                k = value[node]
                if k >= 0:
                    total, end = here + score[k], i + 1
                    if total > best[end & mask]:
                        best[end & mask], come[end] = total, k
                    single = single or end == at + width
            if not single:
                total, end = here + unknown, at + width
                if total > best[end & mask]:
                    best[end & mask], come[end] = total, -1
            at += width
        out, at = array("i"), n
        while at:
            k = come[at]
            if k >= 0:
                out.append(self.ids[k])
                at -= self.size[k]
                continue
            start = at - 1
            while text[start] & 0xC0 == 0x80:
                start -= 1
            if self.bytes:
                out.extend(self.bytes[b] for b in reversed(text[start:at]))
            else:
                out.append(self.unk)
            at = start
        out.reverse()
        return out

    def encode(self, text: str) -> np.ndarray:
        if not text:
            return np.empty(0, np.uint32)
        if not self.breaks:
            return np.frombuffer(self.known[MARK + text.replace(" ", MARK)], np.uint32)
        return np.frombuffer(b"".join(self._blocks(text)), np.uint32)

    def _blocks(self, text: str) -> Iterator[bytes]:
        """Ids of the text's parts of about ``BLOCK`` characters, cut where the best path breaks."""
        at, lead = 0, MARK
        while at < len(text):
            cut = _CUT.search(text, at + BLOCK)
            to = cut.start() if cut else len(text)
            yield b"".join(map(self.known.__getitem__, _BREAK.split(lead + text[at:to].replace(" ", MARK))))
            at, lead = to, ""

    def decode(self, ids: np.ndarray) -> str:
        """Pieces joined, bytes put together, markers back to spaces, the leading one dropped."""
        raw = b"".join(b"".join(map(self.text.__getitem__, ids[k : k + BLOCK].tolist())) for k in range(0, len(ids), BLOCK))
        return raw.decode("utf-8", "replace").replace(MARK, " ")[1:]


#: Characters (or ids) handled at one time; a space after another character, where a part may begin.
BLOCK, _CUT = 1 << 16, re.compile("(?<=[^ ▁]) ")
_BREAK = re.compile(f"(?<=[^{MARK}])(?={MARK})")


class _Segments(dict):
    def __init__(self, pieces: Pieces):
        super().__init__()
        self.pieces = pieces

    def __missing__(self, part: str) -> bytes:
        found = self.pieces.segment(part).tobytes()
        if len(self) >= REMEMBERED:
            self.clear()
        if len(part) < 64:
            self[part] = found
        return found


_LOADED: dict[str, Pieces] = CACHES.setdefault("pieces", {})


def load(path: str) -> Pieces:
    if path not in _LOADED:
        _LOADED[path] = Pieces(path)
    return _LOADED[path]


def encode(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, ids: the piece ids of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = load(path)
        for b in batches:
            for i in range(0, b.num_rows, 512):
                ids = [pieces.encode(t.as_py() or "").astype(np.int32) for t in b.column(1)[i : i + 512]]
                yield pa.RecordBatch.from_arrays([b.column(0)[i : i + 512], pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run, "pieces"), "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, text of encoded rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = load(path)
        for b in batches:
            texts = [pieces.decode(np.array(x.as_py() or [], np.int64)) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.selectExpr("cast(doc_id as long) doc_id", "ids").mapInArrow(lean(run, "pieces"), "doc_id long, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Ids, and digests of them and of the text decoded from them, in one pass over the texts."""
    schema = "doc_id long, n_pieces long, ids array<int>, ids_crc32 long, decoded_sha256 string, round_trip boolean"
    names = [x.strip().split(" ")[0] for x in schema.split(",")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = load(path)
        for b in batches:
            for i in range(0, b.num_rows, 128):
                texts = [t or "" for t in b.column(1)[i : i + 128].to_pylist()]
                ids = [pieces.encode(t) for t in texts]
                back = [pieces.decode(x) for x in ids]
                sizes = [len(x) for x in ids]
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(np.concatenate(ids).astype(np.int32)))
                columns = [
                    b.column(0)[i : i + 128],
                    pa.array(sizes, pa.int64()),
                    lists,
                    pa.array([zlib.crc32(x.tobytes()) for x in ids], pa.int64()),
                    pa.array([hashlib.sha256(x.encode()).hexdigest() for x in back]),
                    pa.array([x == t.replace(MARK, " ") for x, t in zip(back, texts, strict=True)]),
                ]
                yield pa.RecordBatch.from_arrays(columns, names)

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(lean(run, "pieces"), schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))
