"""Standing queries: automata that are built beforehand and fed symbol by symbol."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Sequence

from winsub.kernel.scan import borders


class OnePattern:
    """Failure-function automaton; the state is one integer."""

    def __init__(self, pattern: Sequence):
        if not len(pattern):
            raise ValueError("an empty pattern")
        self.pattern, self.fail, self.state, self.seen = pattern, borders(pattern)[0], 0, 0

    def feed(self, sym) -> int | None:
        """Offset of the match that ends with this symbol, if any."""
        k = self.state
        if k == len(self.pattern):
            k = self.fail[k - 1]
        while k and self.pattern[k] != sym:
            k = self.fail[k - 1]
        if self.pattern[k] == sym:
            k += 1
        self.state = k
        self.seen += 1
        return self.seen - k if k == len(self.pattern) else None


class ManyPatterns:
    """Goto and fail automaton of a pattern set; the state is one integer for all patterns."""

    def __init__(self, patterns: Iterable[str]):
        self.patterns = sorted(set(patterns))
        if "" in self.patterns:
            raise ValueError("an empty pattern")
        self.goto, self.out, self.fail = [{}], [[]], [0]
        for p in self.patterns:
            s = 0
            for c in p:
                if c not in self.goto[s]:
                    self.goto[s][c] = len(self.goto)
                    self.goto.append({})
                    self.out.append([])
                    self.fail.append(0)
                s = self.goto[s][c]
            self.out[s].append(p)
        queue = deque(self.goto[0].values())
        while queue:
            s = queue.popleft()
            for c, t in self.goto[s].items():
                queue.append(t)
                f = self.fail[s]
                while f and c not in self.goto[f]:
                    f = self.fail[f]
                self.fail[t] = self.goto[f].get(c, 0)
                self.out[t] = self.out[t] + self.out[self.fail[t]]

    def step(self, state: int, sym: str) -> int:
        while state and sym not in self.goto[state]:
            state = self.fail[state]
        return self.goto[state].get(sym, 0)

    def run(self, text: Iterable[str], state: int = 0, offset: int = 0) -> tuple[list[tuple[str, int]], int]:
        """[(pattern, offset of its match)], state after the text."""
        found = []
        for i, sym in enumerate(text, offset):
            state = self.step(state, sym)
            found += [(p, i - len(p) + 1) for p in self.out[state]]
        return found, state
