"""Scans of a window for one pattern; all report overlapping matches and their work."""

from __future__ import annotations

from collections.abc import Sequence


def borders(pattern: Sequence) -> tuple[list[int], int]:
    """Length of the longest proper border of every prefix, and comparisons made."""
    out, k, compares = [0] * len(pattern), 0, 0
    for i in range(1, len(pattern)):
        while True:
            compares += 1
            if pattern[i] == pattern[k]:
                k += 1
                break
            if not k:
                break
            k = out[k - 1]
        out[i] = k
    return out, compares


def kmp_find(text: Sequence, pattern: Sequence) -> tuple[list[int], int]:
    """Failure-function scan: linear in text and pattern."""
    fail, compares = borders(pattern)
    found, k, m = [], 0, len(pattern)
    for i, sym in enumerate(text):
        while True:
            compares += 1
            if pattern[k] == sym:
                k += 1
                break
            if not k:
                break
            k = fail[k - 1]
        if k == m:
            found.append(i - m + 1)
            k = fail[k - 1]
            if m == 1:
                k = 0
    return found, compares


def skip_find(text: Sequence, pattern: Sequence) -> tuple[list[int], int]:
    """Right-to-left scan with bad-symbol and good-suffix shifts; after a match, the period."""
    m, n, compares = len(pattern), len(text), 0
    last = {s: i for i, s in enumerate(pattern)}
    # good[j]: shift when pattern[j:] matched and pattern[j-1] did not; good[0]: the period.
    good, border, i, j = [0] * (m + 1), [0] * (m + 1), m, m + 1
    border[m] = m + 1
    while i:
        while j <= m and pattern[i - 1] != pattern[j - 1]:
            compares += 1
            if not good[j]:
                good[j] = j - i
            j = border[j]
        i, j = i - 1, j - 1
        border[i] = j
    j = border[0]
    for i in range(m + 1):
        if not good[i]:
            good[i] = j
        if i == j:
            j = border[j]
    found, at = [], 0
    while at <= n - m:
        j = m
        while j and pattern[j - 1] == text[at + j - 1]:
            compares += 1
            j -= 1
        if not j:
            found.append(at)
            at += good[0]
        else:
            compares += 1
            at += max(good[j], j - 1 - last.get(text[at + j - 1], -1))
    return found, compares


def native_find(text: str, pattern: str) -> tuple[list[int], int]:
    """The string type's own search, restarted one symbol after each match."""
    found, at = [], text.find(pattern)
    while at >= 0:
        found.append(at)
        at = text.find(pattern, at + 1)
    return found, len(text)
