"""Indexes of a frozen text: suffix array with binary search, and backward search."""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Sequence

import numpy as np


def suffix_array(text: Sequence) -> np.ndarray:
    """Offsets of suffixes in order, by prefix doubling; a prefix sorts before the longer."""
    n = len(text)
    if not n:
        return np.empty(0, np.int64)
    if isinstance(text, str):
        codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    else:
        codes = np.asarray(text)
    rank = np.unique(codes, return_inverse=True)[1].astype(np.int64) + 1
    width = 1
    while True:
        second = np.zeros(n, np.int64)
        second[: n - width] = rank[width:]
        order = np.lexsort((second, rank))
        new = (np.diff(rank[order], prepend=-1) != 0) | (np.diff(second[order], prepend=-1) != 0)
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(new)
        if rank.max() == n or width >= n:
            return order
        width *= 2


class SuffixArray:
    """Binary search over suffixes: O(m log w + occ)."""

    def __init__(self, text: str):
        self.text, self.order = text, suffix_array(text)

    def find(self, pattern: str) -> tuple[list[int], int]:
        m, text = len(pattern), self.text
        key = lambda off: text[off : off + m]
        lo = bisect_left(self.order, pattern, key=key)
        hi = bisect_right(self.order, pattern, lo, key=key)
        return sorted(self.order[lo:hi].tolist()), 2 * m * max(1, len(text).bit_length()) + hi - lo


class BackwardSearch:
    """Full-text index of the symbol before each suffix: counts in O(m), then looks offsets up."""

    END = -1

    def __init__(self, text: str, step: int = 64, order: np.ndarray | None = None):
        order = suffix_array(text) if order is None else order
        self.order = np.concatenate([[len(text)], order])
        codes = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.int64)
        self.last = np.where(self.order > 0, np.append(codes, self.END)[self.order - 1], self.END)
        symbols, counts = np.unique(self.last, return_counts=True)
        self.before = dict(zip(symbols.tolist(), (np.cumsum(counts) - counts).tolist(), strict=True))
        self.step = step
        self.marks = {c: np.concatenate([[0], np.cumsum(self.last == c)[step - 1 :: step]]) for c in self.before}

    def _rank(self, c: int, i: int) -> tuple[int, int]:
        """(steps, how often c stands before place i): a mark and a scan behind it."""
        block = i // self.step
        return 1 + i - block * self.step, int(self.marks[c][block] + (self.last[block * self.step : i] == c).sum())

    def find(self, pattern: str) -> tuple[list[int], int]:
        lo, hi, work = 0, len(self.order), 0
        for ch in reversed(pattern):
            c = ord(ch)
            work += 1
            if c not in self.before:
                return [], work
            (one, low), (two, high) = self._rank(c, lo), self._rank(c, hi)
            lo, hi, work = self.before[c] + low, self.before[c] + high, work + one + two
            if lo >= hi:
                return [], work
        return sorted(self.order[lo:hi].tolist()), work + hi - lo
