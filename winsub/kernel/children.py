"""Child containers of index nodes: hashed, sorted and dense, with counted comparisons."""

from __future__ import annotations

from bisect import bisect_left


class Compares:
    """Key comparisons of all containers of one index."""

    def __init__(self):
        self.n = 0


class HashKids(dict):
    """One probe a lookup."""

    __slots__ = ("tally",)

    def __init__(self, tally: Compares):
        super().__init__()
        self.tally = tally

    def get(self, sym, default=None):
        self.tally.n += 1
        return dict.get(self, sym, default)

    def remove(self, sym) -> None:
        del self[sym]

    def take(self, other: HashKids) -> HashKids:
        """Hold what ``other`` holds; nothing is counted."""
        dict.update(self, other)
        return self


class SortedKids:
    """Symbols in order: a lookup bisects, which costs a factor log of the alphabet."""

    __slots__ = ("keys", "nodes", "tally")

    def __init__(self, tally: Compares):
        self.keys, self.nodes, self.tally = [], [], tally

    def _at(self, sym) -> tuple[int, bool]:
        self.tally.n += max(1, len(self.keys).bit_length())
        i = bisect_left(self.keys, sym)
        return i, i < len(self.keys) and self.keys[i] == sym

    def get(self, sym, default=None):
        i, found = self._at(sym)
        return self.nodes[i] if found else default

    def __setitem__(self, sym, node) -> None:
        i, found = self._at(sym)
        if found:
            self.nodes[i] = node
        else:
            self.keys.insert(i, sym)
            self.nodes.insert(i, node)

    def remove(self, sym) -> None:
        i, _ = self._at(sym)
        del self.keys[i], self.nodes[i]

    def take(self, other: SortedKids) -> SortedKids:
        self.keys, self.nodes = other.keys[:], other.nodes[:]
        return self

    def __len__(self) -> int:
        return len(self.keys)

    def values(self):
        return self.nodes


class DenseKids:
    """A slot for every symbol met so far: for tiny alphabets."""

    __slots__ = ("codes", "count", "slots", "tally")

    def __init__(self, tally: Compares, codes: dict):
        self.slots, self.codes, self.count, self.tally = [None] * len(codes), codes, 0, tally

    def get(self, sym, default=None):
        self.tally.n += 1
        code = self.codes.get(sym, -1)
        node = self.slots[code] if 0 <= code < len(self.slots) else None
        return default if node is None else node

    def __setitem__(self, sym, node) -> None:
        code = self.codes.setdefault(sym, len(self.codes))
        if code >= len(self.slots):
            self.slots.extend([None] * (code + 1 - len(self.slots)))
        self.count += self.slots[code] is None
        self.slots[code] = node

    def remove(self, sym) -> None:
        self.slots[self.codes[sym]] = None
        self.count -= 1

    def take(self, other: DenseKids) -> DenseKids:
        if len(self.codes) < len(other.codes):
            self.codes.update(other.codes)
        self.slots, self.count = other.slots[:], other.count
        return self

    def __len__(self) -> int:
        return self.count

    def values(self):
        return [x for x in self.slots if x is not None]


def factory(kind: str):
    """A maker of empty containers that share one tally."""
    tally = Compares()
    if kind == "hash":
        return lambda: HashKids(tally), tally
    if kind == "sorted":
        return lambda: SortedKids(tally), tally
    if kind == "dense":
        codes: dict = {}
        return lambda: DenseKids(tally, codes), tally
    raise ValueError(f"children: {kind!r}")
