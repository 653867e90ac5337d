"""N-gram Jaccard join by parity sketches: links of similarity 3/4 and above, exactly.

``op6_parity_join`` gives components: it finds links enough to connect them, no others.
``op6_all_links`` gives every document's number of links too: it compares each pair of
classes with a common key, in whatever component, so its work grows with the square of a
group of near copies, as its links do.

A parity sketch deals a document's shingles to M blocks and keeps the XOR of the hashes
dealt to each: one shingle more or less changes one block, so the number of differing
blocks is at most the symmetric difference, and two sets with Jaccard similarity of 3/4
differ in at most (|A|+|B|)/7 shingles.  Per size band (``RATIO`` wide, M is 16 times the
band's largest size) the pigeonhole principle therefore leaves common non-empty blocks: in
any one order of blocks, documents that link share one among their first D+1 (D: the
differences allowed).  Those blocks are the join keys.  Blocks of frequent shingles only,
found by a bounded Misra-Gries summary, come last in the order, so boilerplate makes no keys
as long as a document has enough else.  Sets of fewer than ``SMALL`` shingles use the finest
sketch, a block for every hash; so do, beside their own band, documents with so few
non-empty blocks that they, or a partner, could have too few for the bound.

For components, keys are not expanded into pairs.  Each member of a key's group is first
compared with the group's smallest id.  Workers do that for the documents they hold before
anything is shuffled, so a key that very many documents have sends one row a buffer, not one
a document.  One parity bit per shingle gives a bit sketch whose Hamming distance
must be within the bound before texts are fetched and compared exactly.  This settles
groups of two.  Documents emit ``slack(n)`` more keys than needed, so linked documents share
that many more: one with no more keys in groups of three and above than its partners have
slack shares a group of two with each of them and is settled.  Of the others, connected
ones are contracted, further leaders of the groups are tried (``ROUNDS`` rounds at most, while more
than ``AT_ONCE`` members of groups are left), and members of different components that still share a key are compared, in blocks of
``CHUNK`` members, again by Hamming distance first.

Equality of shingles and blocks is that of 64-bit hashes.

Defined results: null text is empty; documents without words have no shingles and are their
own component; rows with one doc_id are one node (if their texts differ, each row counts the
links of its own text); null doc_ids are linked with nothing and
have a null component; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winsub.llm.common import lean, mix64, shingle_sets, slices, stage, table, utf8
from winsub.llm.components import components

SMALL, RATIO, CHUNK, HEAVY, ROUNDS = 64, 16, 1024, 4096, 2
#: Digests a worker remembers to skip copies inside its partition; bits of the text filter;
#: keys a worker holds to settle their groups; rows of one cluster that a task compares, and
#: of these at one time; classes among which it remembers the pairs it compared; rows that need no
#: further leaders; documents at most that are sent to find their texts.
REMEMBERED, FILTER_BITS, HELD, CLUSTER_ROWS, TOGETHER, COMPARED, AT_ONCE, SENT = 50_000, 1 << 22, 500_000, 1 << 16, 8192, 4096, 100_000, 1 << 19


def bound(a, b):
    """Largest symmetric difference of sets of these sizes with similarity >= 3/4."""
    return (a + b) // 7


def slack(n):
    """Keys emitted beyond those that the bound asks for."""
    return n // 16


def width(n: int) -> int:
    """Bits of the bit sketch: two to four for each shingle, half of that for large sets."""
    return 1 << max(6, ((2 if n <= 1024 else 1) * n - 1).bit_length()) if n else 64


def bit_sketch(hashes: np.ndarray) -> np.ndarray:
    w = width(len(hashes))
    parity = np.bincount((hashes & np.uint64(w - 1)).astype(np.int64), minlength=w) & 1
    return np.packbits(parity.astype(np.uint8)).view(np.uint64)


def halve(sketch: np.ndarray, words: int) -> np.ndarray:
    """A sketch as it would be at a narrower width."""
    while sketch.shape[-1] > words:
        half = sketch.shape[-1] // 2
        sketch = sketch[..., :half] ^ sketch[..., half:]
    return sketch


def _is_heavy(hashes: np.ndarray, heavy: np.ndarray) -> np.ndarray:
    if not len(heavy):
        return np.zeros(len(hashes), bool)
    at = np.searchsorted(heavy, hashes)
    at[at == len(heavy)] = 0
    return heavy[at] == hashes


def _first(element: np.ndarray, heavy: np.ndarray, owner: np.ndarray, most: np.ndarray) -> np.ndarray:
    """Places of each owner's first elements (``most`` of them): those not heavy before heavy ones, then by hash."""
    bits = np.uint64(max(1, int(owner[-1]).bit_length()) if len(owner) else 1)
    place = element >> np.uint64(1) | heavy.astype(np.uint64) << np.uint64(63)
    order = np.argsort(place >> bits | owner.astype(np.uint64) << np.uint64(64) - bits)
    owner = owner[order]
    begin = np.searchsorted(owner, np.arange(len(most)))
    return order[np.arange(len(owner)) - begin[owner] < most[owner]]


def keys(sets: list[np.ndarray], heavy: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Join keys of documents, and whose they are: first blocks of their sketches in the bands they can link in."""
    n = np.array([len(s) for s in sets])
    hashes, doc = np.concatenate(sets), np.repeat(np.arange(len(sets)), n)
    hot, out, owners = _is_heavy(hashes, heavy), [], []
    top = np.full(len(n), SMALL)
    while (top < n).any():
        top = np.where(top < n, top * RATIO, top)
    finest = 3 * n < 4 * SMALL  # a partner, or the document, may be small
    band = n >= SMALL
    for own, blocks, most in ((band, 16 * top, bound(n, np.minimum(top, 4 * n // 3))), (band & (4 * n >= 3 * (top + 1)), 16 * top * RATIO, n // 3)):
        some = own[doc]
        if not some.any():
            continue
        blocks = np.minimum(blocks, 1 << 40)
        h, d = hashes[some], doc[some]
        block = (h >> np.uint64(24)).astype(np.int64) & (blocks[d] - 1)
        order = np.argsort(d << 40 | block)
        d, block = d[order], block[order]
        begin = np.flatnonzero((np.diff(block, prepend=-1) != 0) | (np.diff(d, prepend=-1) != 0))
        word = np.bitwise_xor.reduceat(h[order], begin)
        d = d[begin]
        element = mix64(word ^ mix64((block[begin] + blocks[d]).astype(np.uint64)))
        found = _first(element, np.logical_and.reduceat(hot[some][order], begin), d, most + 1 + slack(n))
        out.append(element[found])
        owners.append(d[found])
        # A set with too few blocks for its bound (n/3 + n/16) has partners with at most 0.87 of their size.
        finest |= own & (8 * np.bincount(d, minlength=len(n)) <= 7 * n)
    some = finest[doc]
    element, d = mix64(hashes[some]), doc[some]
    found = _first(element, hot[some], d, n // 4 + 1 + slack(n))
    return np.concatenate([*out, element[found]]), np.concatenate([*owners, d[found]])


class Frequent:
    """Misra-Gries summary of at most ``size`` counters over hashes."""

    def __init__(self, size: int = HEAVY):
        self.size, self.key, self.count = size, np.empty(0, np.uint64), np.empty(0, np.int64)

    def add(self, hashes: np.ndarray) -> None:
        key, count = np.unique(hashes, return_counts=True)
        key = np.concatenate([self.key, key])
        count = np.concatenate([self.count, count])
        self.key, where = np.unique(key, return_inverse=True)
        self.count = np.bincount(where, weights=count, minlength=len(self.key)).astype(np.int64)
        if len(self.key) > self.size:
            self.count -= np.partition(self.count, -self.size - 1)[-self.size - 1]
            stay = self.count > 0
            self.key, self.count = self.key[stay], self.count[stay]


PROFILE = "doc_id long, n int, digest binary, sketch binary, key long, times long"


def _profile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names, frequent = [x.split(" ")[0] for x in PROFILE.split(", ")], Frequent()
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]
    for b in batches:
        data, offsets = utf8(b.column(1))
        for i, j in slices(offsets):
            sets = shingle_sets(data, offsets[i : j + 1])
            frequent.add(np.concatenate(sets))
            rows = [[len(s) for s in sets], [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], [bit_sketch(s).tobytes() for s in sets]]
            none = [None] * (j - i)
            yield pa.RecordBatch.from_arrays([b.column(0)[i:j], *(pa.array(c, k) for c, k in zip([*rows, none, none], kinds[1:], strict=True))], names)
    if len(frequent.key):
        none = [None] * len(frequent.key)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip([none, none, none, none, frequent.key.view(np.int64), frequent.count], kinds, strict=True)], names)


EMITTED = "place long, doc long, key long, leader long, times long"


def _settle(key: np.ndarray, doc: np.ndarray) -> pa.RecordBatch:
    """Rows of ``EMITTED``: of three and more documents with one key the smallest id leads.

    A leader, or a document of a smaller group, has its key as its place and stands for ``times``
    documents (null: 1); the others have places of their own and name their key and leader.
    """
    order = np.argsort(key)
    first = np.flatnonzero(np.diff(key[order], prepend=key[order[0]] ^ 1))
    size = np.diff(np.append(first, len(key)))
    many = np.repeat(size > 2, size)
    some = order[many]
    order[many] = some[np.lexsort((doc[some], key[some]))]
    key, doc = key[order], doc[order]
    led = many.copy()
    led[first] = False
    times = np.where(led, 0, 1)
    times[first] = np.where(size > 2, size, 1)
    own = mix64(key[led].view(np.uint64) ^ mix64(doc[led].view(np.uint64))).view(np.int64)
    place = key.copy()
    place[led] = own
    columns = [place, doc, pa.array(key, mask=~led), pa.array(np.repeat(doc[first], size), mask=~led), pa.array(times, mask=times == 1)]
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in columns], [x.split(" ")[0] for x in EMITTED.split(", ")])


def _emit(heavy: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        held: list[tuple[np.ndarray, ...]] = []

        def settled() -> Iterator[pa.RecordBatch]:
            if held:
                rows = _settle(*(np.concatenate(x) for x in zip(*held, strict=True)))
                held.clear()
                for k in range(0, rows.num_rows, 1 << 16):
                    yield rows.slice(k, 1 << 16)

        for b in batches:
            data, offsets = utf8(b.column(1))
            ids = b.column(0).to_numpy()
            for i, j in slices(offsets):
                sets, docs = [], []
                for doc, s in zip(ids[i:j], shingle_sets(data, offsets[i : j + 1]), strict=True):
                    digest = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
                    if not len(s) or digest in seen:
                        continue
                    if len(seen) >= REMEMBERED:
                        seen.clear()
                    seen.add(digest)
                    sets.append(s)
                    docs.append(doc)
                if sets:
                    key, owner = keys(sets, heavy)
                    held.append((key.view(np.int64), np.array(docs, np.int64)[owner]))
                if sum(len(x[0]) for x in held) > HELD:
                    yield from settled()
        yield from settled()

    return lean(run)


def _near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose bit sketches are within the bound."""
    for b in batches:
        keep = []
        for na, sa, nb, sb in zip(b.column(2).to_pylist(), b.column(3), b.column(4).to_pylist(), b.column(5), strict=True):
            x, y = np.frombuffer(sa.as_buffer(), np.uint64), np.frombuffer(sb.as_buffer(), np.uint64)
            w = min(len(x), len(y))
            keep.append(int(np.bitwise_count(halve(x, w) ^ halve(y, w)).sum()) <= bound(na, nb))
        yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose shingle sets have a similarity of at least 3/4."""
    for b in batches:
        keep = []
        for k in range(b.num_rows):
            pair = pa.concat_arrays([b.column(2)[k : k + 1], b.column(3)[k : k + 1]])
            x, y = shingle_sets(*utf8(pair))
            both = len(x) + len(y) - len(np.union1d(x, y))
            keep.append(100 * both >= 75 * (len(x) + len(y) - both))
        yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


class _Compared:
    """Which pairs of classes a task compared; it starts afresh after ``COMPARED`` classes."""

    def __init__(self):
        self.index: dict[int, int] = {}
        self.done = np.zeros((COMPARED, COMPARED), bool)

    def places(self, rep: np.ndarray) -> np.ndarray | None:
        """The classes' rows of ``done``; none if they are too many."""
        new = [x for x in rep.tolist() if x not in self.index]
        if len(self.index) + len(new) > COMPARED:
            self.index.clear()
            self.done[:] = False
            new = rep.tolist()
        if len(new) > COMPARED:
            return None
        for x in new:
            self.index[x] = len(self.index)
        return np.array([self.index[x] for x in rep.tolist()])


class _Cluster:
    """The classes of some rows, one a key and class."""

    def __init__(self, rows: pa.Table, compared: _Compared):
        self.rep, first, self.local = np.unique(rows["rep"].to_numpy(), return_index=True, return_inverse=True)
        self.n, self.label = (rows[x].to_numpy()[first] for x in ("n", "label"))
        self.sketches = [np.frombuffer(x.as_buffer(), np.uint64) for x in rows["sketch"].take(pa.array(first))]
        self.words = np.array([len(x) for x in self.sketches])
        self.halved: dict[int, np.ndarray] = {}
        self.done, self.place = compared.done, compared.places(self.rep)

    def at(self, w: int) -> np.ndarray:
        """All sketches at ``w`` words (zeros for narrower ones)."""
        if w not in self.halved:
            self.halved[w] = np.stack([halve(x, w) if len(x) >= w else np.zeros(w, np.uint64) for x in self.sketches])
        return self.halved[w]

    def near(self, one: np.ndarray, other: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (places of one, places of other) of different components that are within the bound, compared once."""
        n, label = self.n, self.label
        small, large = np.minimum(n[one][:, None], n[other]), np.maximum(n[one][:, None], n[other])
        open_ = (label[one][:, None] != label[other]) & (4 * small >= 3 * large)
        if one is other:
            open_ &= np.tri(len(one), k=-1, dtype=bool)
        if self.place is not None:
            open_ &= ~self.done[self.place[one][:, None], self.place[other]]
        a, b = np.nonzero(open_)
        a, b = one[a], other[b]
        if self.place is not None:
            x, y = self.place[a], self.place[b]
            self.done[x, y] = self.done[y, x] = True
        width, hit = np.minimum(self.words[a], self.words[b]), np.zeros(len(a), bool)
        for w in np.unique(width):
            m, of = self.at(w), np.flatnonzero(width == w)
            for k in range(0, len(of), 1 << 15):
                some = of[k : k + (1 << 15)]
                far = np.bitwise_count(m[a[some]] ^ m[b[some]]).sum(axis=1, dtype=np.int32)
                hit[some] = far <= bound(n[a[some]], n[b[some]])
        return a[hit], b[hit]


_BLOCK = ["key", "low", "high"]


def _cross(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Near pairs of each run of equal (key, low, high); a run has about 2 * CHUNK rows."""
    held: list[pa.RecordBatch] = []
    compared = _Compared()

    def starts(rows: pa.Table) -> np.ndarray:
        new = np.zeros(rows.num_rows, bool)
        new[0] = True
        for x in _BLOCK:
            v = rows[x].to_numpy()
            new[1:] |= v[1:] != v[:-1]
        return np.flatnonzero(new)

    def out(rows: pa.Table) -> pa.RecordBatch:
        cluster, chunk, low, high = _Cluster(rows, compared), *(rows[x].to_numpy() for x in ("chunk", "low", "high"))
        a, b = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        new = starts(rows)
        for i, j in zip(new, np.append(new[1:], len(chunk)), strict=True):
            one = cluster.local[i:j]
            if low[i] == high[i]:
                found = cluster.near(one, one)
            else:
                first = chunk[i:j] == low[i]
                found = cluster.near(one[first], one[~first])
            a.append(found[0])
            b.append(found[1])
        a, b = cluster.rep[np.concatenate(a)], cluster.rep[np.concatenate(b)]
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])

    for b in batches:
        held.append(b)
        if sum(x.num_rows for x in held) >= TOGETHER:
            rows = pa.Table.from_batches(held)
            cut = int(starts(rows)[-1])
            if cut:
                yield out(rows.slice(0, cut))
                held = rows.slice(cut).combine_chunks().to_batches()
    if held and (rows := pa.Table.from_batches(held)).num_rows:
        yield out(rows)


class Join:
    """The stages of one join over ``docs``."""

    def __init__(self, docs: DataFrame):
        self.texts = docs.selectExpr("cast(doc_id as long) doc_id", "text")
        made = stage(self.texts.mapInArrow(lean(_profile), PROFILE), "profile")
        self.rows = made.where("n is not null").select("doc_id", "n", "digest", "sketch")
        summed = made.where("key is not null").groupBy("key").agg(F.sum("times").alias("times"))
        frequent = summed.where("times >= 64").orderBy(F.desc("times"), "key").limit(HEAVY).select("key").toPandas()
        self.heavy = np.sort(frequent["key"].to_numpy(np.int64).view(np.uint64))
        # Equal sets are one class, named by the smallest doc_id.
        sized = self.rows.where("n > 0 and doc_id is not null")
        self.classes = sized.groupBy("digest").agg(F.min("doc_id").alias("rep"))
        self.member = stage(sized.select("doc_id", "n", "digest").join(self.classes, "digest").select("doc_id", "rep", "n"), "member")
        reps = self.member.where("doc_id = rep").select("rep").distinct()
        self.sketch = self.rows.join(reps, self.rows.doc_id == reps.rep, "left_semi").select(F.col("doc_id").alias("rep"), "n", "sketch")

    def keyed(self) -> DataFrame:
        """Members of groups with a common key beside the group's leader.

        ``key`` is null where the group has no third member: its one pair says it all.
        """
        rows = self.texts.where("doc_id is not null").mapInArrow(_emit(self.heavy), EMITTED)
        by = Window.partitionBy("place")  # one row a worker's buffer and key at most, but for groups of two
        lead = rows.withColumn("lead", F.min("doc").over(by)).withColumn("size", F.sum(F.coalesce("times", F.lit(1))).over(by))
        lead = lead.select("doc", F.coalesce("leader", "lead").alias("leader"), F.coalesce("key", F.when(F.col("size") > 2, F.col("place"))).alias("key"))
        return stage(lead.where("doc <> leader").select("key", "doc", "leader").distinct(), "keyed")

    def verified(self, pairs: DataFrame, near: bool) -> DataFrame:
        """(a, b) of classes -> those that link: sizes, then sketches, then texts."""
        if near:
            s = self.sketch
            pairs = pairs.join(s.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa")), "a")
            pairs = pairs.join(s.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb")), "b")
            pairs = pairs.where("100 * least(na, nb) >= 75 * greatest(na, nb)")
            pairs = pairs.select("a", "b", "na", "sa", "nb", "sb").mapInArrow(lean(_near), "a long, b long")
        pairs = stage(pairs.distinct(), "pairs")
        ends = stage(pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct(), "ends")
        texts = stage(self._some(ends).select("doc_id", "text"), "texts")
        full = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a")
        full = full.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b")
        return stage(full.select("a", "b", "ta", "tb").mapInArrow(lean(_verify), "a long, b long").distinct(), "links")

    def _some(self, ends: DataFrame) -> DataFrame:
        """Texts of the given documents: a bounded set is sent; of more, a filter of fixed size spares others the shuffle."""
        if ends.count() <= SENT:
            return self.texts.join(F.broadcast(ends), "doc_id", "left_semi")
        bit = F.pmod(F.xxhash64("doc_id"), F.lit(FILTER_BITS))
        words = ends.groupBy(F.floor(bit / 64).cast("int").alias("w")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(pmod(xxhash64(doc_id), {FILTER_BITS}) % 64 as int))")).alias("m"))
        bits = np.zeros(FILTER_BITS // 64, np.int64)
        found = words.toPandas()  # at most FILTER_BITS / 64 rows
        bits[found["w"].to_numpy()] = found["m"].to_numpy()
        bits = bits.view(np.uint64)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                at = b.column(2).to_numpy()
                yield b.select(["doc_id", "text"]).filter(pa.array((bits[at // 64] >> (at % 64).astype(np.uint64)) & np.uint64(1) == 1))

        passed = self.texts.where("doc_id is not null").withColumn("bit", bit).mapInArrow(run, "doc_id long, text string")
        return passed.join(ends, "doc_id", "left_semi")

    def _classes(self, pairs: DataFrame) -> DataFrame:
        """(doc, leader) -> pairs (a, b), a < b, of their classes."""
        m = self.member.select("doc_id", "rep")
        pairs = pairs.join(m.select(F.col("doc_id").alias("doc"), F.col("rep").alias("x")), "doc")
        pairs = pairs.join(m.select(F.col("doc_id").alias("leader"), F.col("rep").alias("y")), "leader")
        return pairs.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()

    def _unsettled(self, keyed: DataFrame) -> DataFrame:
        """(key, rep, n) of the classes that groups of two don't settle."""
        more = keyed.where("key is not null")
        more = more.select("key", "doc").unionByName(more.select("key", F.col("leader").alias("doc"))).distinct()
        more = stage(more.join(self.member.select(F.col("doc_id").alias("doc"), "rep", "n"), "doc"), "common")
        # The least slack of a partner: 3/4 of the set's size.
        many = more.groupBy("doc").agg(F.count(F.lit(1)).alias("keys"), F.max("n").alias("n")).where("keys > floor(ceil(0.75 * n) / 16)").select("doc")
        rows = more.join(many, "doc", "left_semi").select("key", "rep", "n").distinct()
        shared = rows.groupBy("key").agg((F.min("rep") < F.max("rep")).alias("open")).where("open").select("key")
        return stage(rows.join(shared, "key", "left_semi"), "unsettled")

    @staticmethod
    def _open(rows: DataFrame, label: DataFrame) -> DataFrame:
        """Rows with their components' labels, of keys that more than one component has."""
        rows = rows.join(label.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", "n", F.coalesce("label", "rep").alias("label"))
        shared = rows.groupBy("key").agg((F.min("label") < F.max("label")).alias("open")).where("open").select("key")
        return stage(rows.join(shared, "key", "left_semi"), "open")

    def links(self) -> DataFrame:
        """Links of classes that connect all components: (a, b)."""
        keyed = self.keyed()
        found = self.verified(self._classes(keyed.select("doc", "leader").distinct()), near=True)
        label = components(found)
        rows = self._open(self._unsettled(keyed), label)
        for k in range(ROUNDS):
            if rows.count() <= AT_ONCE:
                break
            place = F.xxhash64("rep", F.lit(k))
            lead = rows.groupBy("key").agg(F.min_by("rep", place).alias("leader"), F.min_by("label", place).alias("own"))
            pairs = rows.join(lead, "key").where("label <> own")
            pairs = pairs.select(F.least("rep", "leader").alias("a"), F.greatest("rep", "leader").alias("b")).distinct()
            # What is known of the components is a star below each label.
            found = label.select(F.col("node").alias("a"), F.col("label").alias("b")).unionByName(self.verified(pairs, near=True))
            label = components(found)
            rows = self._open(rows.select("key", "rep", "n"), label)
        return label.select(F.col("node").alias("a"), F.col("label").alias("b")).unionByName(self._compared(rows))

    def all_links(self) -> DataFrame:
        """Every link of two classes, once: (a, b), a < b."""
        rows = self.texts.where("doc_id is not null").mapInArrow(_emit(self.heavy), EMITTED).select(F.coalesce("key", "place").alias("key"), "doc")
        rows = rows.join(self.member.select(F.col("doc_id").alias("doc"), "rep", "n"), "doc").select("key", "rep", "n").distinct()
        # Each class is its own label, so that none of its pairs is left out.
        nobody = rows.sparkSession.createDataFrame([], "node long, label long")
        return self._compared(self._open(stage(rows, "all"), nobody))

    def _compared(self, left: DataFrame) -> DataFrame:
        """Links between the rows (key, rep, n, label) of a key whose labels differ."""
        # Keys of one cluster mostly have the same least member: their runs meet in one task, which
        # then gives each pair once; a large cluster's keys are dealt to tasks of about CLUSTER_ROWS
        # rows.  A document's place in a large group is its own.
        sizes = stage(left.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.min(F.xxhash64("rep")).alias("home")), "sizes")
        homes = sizes.groupBy("home").agg(F.ceil(F.sum("size") / CLUSTER_ROWS).alias("spread"))
        sizes = sizes.join(homes, "home").select("key", "size", "home", F.expr("pmod(xxhash64(key), spread)").alias("share"))
        parts = F.expr(f"cast(power(2, greatest(0, ceil(log2(size / {CHUNK})))) as int)")
        left = left.join(sizes, "key").withColumn("chunk", F.pmod(F.xxhash64("rep"), parts).cast("int"))
        left = left.join(self.sketch.select("rep", "sketch"), "rep")
        left = left.select("*", F.explode(F.sequence(F.lit(0), parts - 1)).alias("other"))
        left = left.select("home", "share", "key", F.least("chunk", "other").alias("low"), F.greatest("chunk", "other").alias("high"), "chunk", "rep", "n", "label", "sketch")
        runs = left.repartition("home", "share", "low", "high").sortWithinPartitions("home", "share", "low", "high", "key").drop("home", "share")
        return self.verified(runs.mapInArrow(lean(_cross), "a long, b long"), near=False)

    def documents(self) -> DataFrame:
        """doc_id, n_shingles, component_id, class_id, n_links of every row."""
        links = self.all_links()
        size = stage(self.member.select("doc_id", "rep").distinct().groupBy("rep").agg(F.count(F.lit(1)).alias("size")), "size")
        both = links.select(F.col("a").alias("own"), F.col("b").alias("rep")).unionByName(links.select(F.col("b").alias("own"), F.col("a").alias("rep")))
        others = both.join(size, "rep").groupBy(F.col("own").alias("rep")).agg(F.sum("size").alias("others"))
        found = size.join(others, "rep", "left").join(components(links).withColumnRenamed("node", "rep"), "rep", "left")
        found = found.select("rep", (F.col("size") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("label", "rep").alias("label"))
        # A doc_id with several texts is one node of the smallest class's component.
        named = self.member.groupBy("doc_id").agg(F.min("rep").alias("rep")).join(found.select("rep", "label"), "rep").select("doc_id", F.col("label").alias("component_id"))
        rows = self.rows.where("doc_id is not null").join(self.classes, "digest", "left").select("doc_id", "n", "rep")
        rows = rows.unionByName(self.rows.where("doc_id is null").select("doc_id", "n", F.lit(None).cast("long").alias("rep")))
        rows = rows.join(found.select("rep", "n_links"), "rep", "left").join(named, "doc_id", "left")
        return rows.select(
            "doc_id",
            F.col("n").cast("long").alias("n_shingles"),
            F.coalesce("component_id", "doc_id").alias("component_id"),
            F.coalesce("rep", "doc_id").alias("class_id"),
            F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        )

    def components(self) -> DataFrame:
        """doc_id, n_shingles, component_id of every row."""
        label = components(self.links())
        named = self.member.groupBy("doc_id").agg(F.min("rep").alias("rep")).join(label.withColumnRenamed("node", "rep"), "rep", "left")
        named = named.select("doc_id", F.coalesce("label", "rep").alias("component_id"))
        return self.rows.join(named, "doc_id", "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    return Join(docs).components()


def kept_documents(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay: the smallest doc_id of each component; all columns."""
    lost = near_duplicates(docs).where("doc_id <> component_id").select(F.col("doc_id").alias("_lost")).distinct()
    lost = stage(lost, "lost")
    return docs.join(lost, docs.doc_id.cast("long") == lost._lost, "left_anti").select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def all_links_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Join(table(spark, sf_dir, "documents")).documents()
