"""Live windows: one state a stream, symbols and ad-hoc queries in one ordered input.

Input rows: (stream_id, seq, kind 'sym' | 'query', payload), ``seq`` ordering a stream's
rows.  A query sees the window as of its place: updates and queries of a stream are taken
one after the other, streams run in parallel.  State layouts: ``text`` keeps the window's
text and builds the index in every batch, ``text+lazy`` builds it only when a batch has
queries, ``tree`` keeps the index itself.
"""

from __future__ import annotations

import contextlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from winsub.kernel.automaton import ManyPatterns
from winsub.kernel.scan import native_find
from winsub.kernel.window_index import WindowIndex
from winsub.model import MATCHES, names

LAYOUTS = ("text", "text+lazy", "tree")
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


@contextlib.contextmanager
def state_store(spark: SparkSession):
    """Keyed state needs the RocksDB provider; the session's own choice is put back."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, ROCKS)
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


class LiveWindow(StatefulProcessor):
    def __init__(self, capacity: int, layout: str = "text+lazy", idle_ms: int | None = None):
        if layout not in LAYOUTS:
            raise ValueError(f"layout: {layout!r}")
        self.capacity, self.layout, self.idle_ms = capacity, layout, idle_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        schema = "n_seen bigint, win_text string, tree binary"
        self.state = handle.getValueState("window", schema, self.idle_ms) if self.idle_ms else handle.getValueState("window", schema)

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        batch = pd.concat(list(rows)).sort_values(["seq", "kind"], ascending=[True, False], kind="stable")
        n, text, tree = self.state.get() if self.state.exists() else (0, "", None)
        asked = (batch.kind == "query").any()
        index, added, out = None, [], []
        if self.layout == "tree":
            index = WindowIndex.restore(bytes(tree)) if tree else WindowIndex(self.capacity)
        elif asked or self.layout == "text":
            index = WindowIndex(self.capacity)
            index.start = index.n_seen = index._base = n - len(text)
            index.extend(text)
        for kind, payload in zip(batch.kind, batch.payload, strict=True):
            if kind == "sym":
                n += 1
                if index is None:
                    added.append(payload)
                else:
                    index.push(payload)
            else:
                out += [(key[0], payload, n, off) for off in index.locate(payload)]
        text = "".join(index.window()) if index is not None else (text + "".join(added))[-self.capacity :]
        self.state.update((n, text if self.layout != "tree" else "", index.snapshot() if self.layout == "tree" else None))
        yield pd.DataFrame(out, columns=names(MATCHES))

    def close(self) -> None:
        pass


ORDERED = "stream_id string, ts timestamp, seq bigint, payload string, late boolean"


class Reorder(StatefulProcessor):
    """Holds symbols until the watermark has passed them and gives them in order of time.

    Symbols behind the watermark come out at once, marked late: a dead-letter sink takes them.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.held = handle.getListState("held", "ms bigint, seq bigint, payload string")

    def _rows(self, key, found: list, late: bool) -> pd.DataFrame:
        out = [(key[0], pd.Timestamp(ms, unit="ms"), seq, payload, late) for ms, seq, payload in found]
        return pd.DataFrame(out, columns=names(ORDERED))

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        mark, late, new = timerValues.getCurrentWatermarkInMs(), [], []
        for b in rows:
            for ts, seq, payload in zip(b.ts, b.seq, b.payload, strict=True):
                ms = int(pd.Timestamp(ts).value // 1_000_000)
                (late if ms <= mark else new).append((ms, seq, payload))
        for row in new:
            self.held.appendValue(row)
        if new:
            self.handle.registerTimer(max(ms for ms, _, _ in new))
            self.handle.registerTimer(min(ms for ms, _, _ in new))
        yield self._rows(key, sorted(late), True)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        mark = timerValues.getCurrentWatermarkInMs()
        held = sorted(self.held.get())
        ready, rest = [r for r in held if r[0] <= mark], [r for r in held if r[0] > mark]
        if ready:
            self.held.clear()
            for row in rest:
                self.held.appendValue(row)
            if rest:
                self.handle.registerTimer(rest[0][0])
        yield self._rows(key, ready, False)

    def close(self) -> None:
        pass


def reordered(rows: DataFrame, delay: str) -> DataFrame:
    """Streaming (stream_id, ts, seq, payload) -> the same in order of time, and ``late``."""
    timed = in_event_time(rows.select("stream_id", "ts", "seq", "payload"), "ts", delay)
    return timed.groupBy("stream_id").transformWithStateInPandas(Reorder(), ORDERED, "Append", "EventTime")


def live_locate(tagged: DataFrame, capacity: int, layout: str = "text+lazy", idle_ms: int | None = None) -> DataFrame:
    """Streaming (stream_id, seq, kind, payload) -> streaming MATCHES."""
    mode = "ProcessingTime" if idle_ms else "None"
    return tagged.groupBy("stream_id").transformWithStateInPandas(LiveWindow(capacity, layout, idle_ms), MATCHES, "Append", mode)


def tagged(rows: DataFrame, patterns: list[str], asks: str) -> DataFrame:
    """Symbols (stream_id, seq, sym) and, after each row where ``asks`` holds, all patterns."""
    query = F.transform(F.array(*map(F.lit, patterns)), lambda p: F.struct(F.lit("query").alias("kind"), p.alias("payload")))
    own = F.array(F.struct(F.lit("sym").alias("kind"), F.col("sym").alias("payload")))
    both = F.when(F.expr(asks), F.concat(own, query)).otherwise(own)
    return rows.select("stream_id", "seq", F.explode(both).alias("r")).select("stream_id", "seq", "r.kind", "r.payload")


class SharedWindows(StatefulProcessor):
    """The windows of a group of streams, and queries that ask all of them.

    A query stands after every symbol of its time.  A window is searched once for each pattern,
    however many queries meet it unchanged; each query has its rows.
    """

    def __init__(self, capacity: int):
        self.capacity = capacity

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getMapState("held", "stream_id string", "n_seen bigint, win_text string")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        batch = pd.concat(list(rows))
        asked = batch[batch.kind == "query"].sort_values("at", kind="stable")
        symbols = batch[batch.kind == "sym"].sort_values(["stream_id", "at", "tie", "payload"], kind="stable")
        known = {k[0]: v for k, v in self.held.iterator()}
        new = {sid: (own["at"].to_numpy(), "".join(own.payload)) for sid, own in symbols.groupby("stream_id", sort=False)}
        times = {p: own["at"].to_numpy() for p, own in asked.groupby("payload", sort=False)}
        out, rows_held = [], 0
        for sid in known.keys() | new.keys() if times else new:
            seen, before = known.get(sid, (0, ""))
            at, text = new.get(sid, (np.empty(0, np.int64), ""))
            whole, first = before + text, seen - len(before)
            for p, when in times.items():
                ends, times_met = np.unique(np.searchsorted(at, when, side="right"), return_counts=True)
                for end, n in zip((seen + ends).tolist(), times_met.tolist(), strict=True):
                    start = max(first, end - self.capacity)
                    found = [start + i for i in native_find(whole[start - first : end - first], p)[0]]
                    if found:
                        out.append((sid, p, end, found, n))
                        rows_held += n * len(found)
            if rows_held > 200_000:
                yield self._matches(out)
                out, rows_held = [], 0
            if text:
                self.held.updateValue((sid,), (seen + len(text), whole[-self.capacity :]))
        yield self._matches(out)

    @staticmethod
    def _matches(found: list[tuple]) -> pd.DataFrame:
        """A row for each query and match."""
        columns = [(sid, p, end, off) for sid, p, end, offs, _ in found for off in offs]
        times = [n for *_, offs, n in found for _ in offs]
        one = pd.DataFrame(columns, columns=names(MATCHES))
        return one.loc[one.index.repeat(times)].reset_index(drop=True)

    def close(self) -> None:
        pass


def locate_all(rows: DataFrame, asked: DataFrame, capacity: int, groups: int = 256) -> DataFrame:
    """Streaming (stream_id, at, tie, sym) and streaming queries (at, pattern) -> streaming MATCHES.

    Every query asks the window of every stream that has a symbol by its time.  Streams are dealt
    out into groups and a query goes to each group, not to each stream; of a group the symbols
    and queries of one micro-batch meet in a task, so ``groups`` is to grow with the streams.
    """
    own = rows.where("stream_id is not null and sym is not null")
    own = own.select(F.pmod(F.xxhash64("stream_id"), F.lit(groups)).alias("part"), "stream_id", "at", "tie", F.lit("sym").alias("kind"), F.col("sym").alias("payload"))
    each = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("part")
    sent = asked.where("length(pattern) > 0").select(each, F.lit(None).cast("string").alias("stream_id"), "at", F.lit(0).cast("long").alias("tie"), F.lit("query").alias("kind"), F.col("pattern").alias("payload"))
    return own.unionByName(sent).groupBy("part").transformWithStateInPandas(SharedWindows(capacity), MATCHES, "Append", "None")


def standing_match(rows: DataFrame, patterns: list[str]) -> DataFrame:
    """Streaming (stream_id, seq, sym) -> streaming MATCHES of patterns known beforehand.

    The state of a stream is one automaton state and the number of symbols read.
    """
    machine = ManyPatterns(patterns)

    def feed(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        at, n = state.get if state.exists else (0, 0)
        batch = pd.concat(list(batches)).sort_values("seq", kind="stable")
        found, at = machine.run(batch.sym, at, n)
        state.update((at, n + len(batch)))
        yield pd.DataFrame([(key[0], p, off + len(p), off) for p, off in found], columns=names(MATCHES))

    return rows.groupBy("stream_id").applyInPandasWithState(feed, MATCHES, "at int, n bigint", "append", GroupStateTimeout.NoTimeout)


def standing_match_batch(texts: DataFrame, patterns: list[str]) -> DataFrame:
    """(stream_id, text) -> MATCHES by the same automaton."""
    machine = ManyPatterns(patterns)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = [(sid, p, off + len(p), off) for sid, t in zip(b.stream_id, b.text, strict=True) for p, off in machine.run(t)[0]]
            yield pd.DataFrame(out, columns=names(MATCHES))

    return texts.select("stream_id", "text").mapInPandas(run, MATCHES)


def in_event_time(rows: DataFrame, ts: str, delay: str) -> DataFrame:
    """A watermark on a time column without a zone: it is read as UTC first."""
    return rows.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def once(rows: DataFrame, keys: list[str], ts: str, delay: str) -> DataFrame:
    """Drops what an at-least-once source sends again within the delay."""
    return in_event_time(rows, ts, delay).dropDuplicatesWithinWatermark(keys)


def counts(rows: DataFrame, ts: str, delay: str, size: str, slide: str | None = None, session: bool = False, key: str | None = None) -> DataFrame:
    """Rows a window of event time: tumbling, sliding, or sessions with a gap."""
    timed = in_event_time(rows, ts, delay)
    window = F.session_window(ts, size) if session else F.window(ts, size, slide)
    keys = [window.alias("w")] + ([F.col(key)] if key else [])
    return timed.groupBy(*keys).agg(F.count(F.lit(1)).alias("cnt"))


def near_events(left: DataFrame, right: DataFrame, key: str, within: str) -> DataFrame:
    """Stream-stream join of rows of one key at most ``within`` apart; both sides have ``ts``."""
    a, b = in_event_time(left, "ts", within).alias("a"), in_event_time(right, "ts", within).alias("b")
    cond = f"a.{key} = b.{key} and b.ts between a.ts - interval {within} and a.ts + interval {within}"
    return a.join(b, F.expr(cond))
