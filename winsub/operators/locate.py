"""All offsets of patterns in windows, by the index or by any baseline."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winsub.kernel.automaton import ManyPatterns
from winsub.kernel.scan import kmp_find, native_find, skip_find
from winsub.kernel.static_index import BackwardSearch, SuffixArray
from winsub.kernel.window_index import WindowIndex
from winsub.model import MATCHES
from winsub.plans.planner import choose_method, gram_pairs, sendable

KERNEL = ("index", "kmp", "boyer_moore", "finalise", "static_bwt", "suffix_array", "native")
METHODS = (*KERNEL, "automaton", "sql", "catalyst", "auto")


def matcher(patterns: list[str]) -> Callable[[str], Iterator[tuple[str, int]]]:
    """text -> (pattern, place) of all matches in one pass, however many patterns there are."""
    try:
        import ahocorasick
    except ImportError:
        machine = ManyPatterns(patterns)
        return lambda text: iter(machine.run(text)[0])
    machine = ahocorasick.Automaton()
    for p in patterns:
        machine.add_word(p, p)
    if not patterns:
        return lambda text: iter(())
    machine.make_automaton()
    return lambda text: ((p, end - len(p) + 1) for end, p in machine.iter(text))


def finder(text: str, start: int, method: str, rule: str, ancestor: str, children: str) -> Callable[[str], list[int]]:
    """pattern -> offsets in one window, everything that can be shared built once."""
    if method in ("index", "finalise"):
        index = WindowIndex(max(1, len(text)), children=children, ancestor=ancestor)
        index.start = index.n_seen = index._base = start
        index.extend(text)
        if method == "finalise":
            return lambda p: index.finalised().locate(p, rule=rule, ordered=False)  # closed anew for every query
        return lambda p: index.locate(p, rule=rule, ordered=False)
    if method in ("suffix_array", "static_bwt"):
        static = SuffixArray(text) if method == "suffix_array" else BackwardSearch(text)
        return lambda p: [start + i for i in static.find(p)[0]]
    scan = {"kmp": kmp_find, "boyer_moore": skip_find, "native": native_find, "automaton": native_find}[method]
    return lambda p: [start + i for i in scan(text, p)[0]]


def _emit(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["stream_id", "query_id", "n_seen", "off"])


def positions(text: str = "win_text", pattern: str = "pattern") -> F.Column:
    """Array of 0-based match places as one JVM expression: one pass splits before each match."""
    pieces = f"split({text}, concat('(?=\\\\Q', replace({pattern}, '\\\\E', '\\\\E\\\\\\\\E\\\\Q'), '\\\\E)'), -1)"
    starts = f"aggregate(slice(pieces, 1, size(pieces) - 1), named_struct('at', 0, 'out', if(startswith({text}, {pattern}), array(0), cast(array() as array<int>))), (a, x) -> named_struct('at', a.at + char_length(x), 'out', array_append(a.out, a.at + char_length(x))), a -> a.out)"
    return F.expr(starts.replace("pieces", pieces))


def locate(windows: DataFrame, queries: DataFrame, method: str = "auto", rule: str = "project", ancestor: str = "order_list", children: str = "hash", parallel: str = "stream") -> DataFrame:
    """WINDOWS, QUERIES -> MATCHES.

    Null texts and patterns give no rows; an empty pattern raises.  ``parallel='query'``
    deals (window, query) pairs instead of windows, for few windows and many queries.
    """
    if method not in METHODS:
        raise ValueError(f"method: {method!r}")
    if queries.where("pattern = ''").limit(1).count():
        raise ValueError("an empty pattern")
    windows = windows.where("win_text is not null and stream_id is not null")
    sent = sendable(queries)
    if parallel == "segment":
        return _by_segment(windows, queries, sent)
    if method == "auto":
        size = windows.agg(F.avg(F.length("win_text"))).first()[0] or 1
        if sent is not None:
            method = "catalyst" if len(sent) <= 8 else "automaton"
        else:
            method = choose_method(1, size)
    if method in ("sql", "catalyst"):
        return _declared(windows, queries, method, sent)
    if method == "automaton" and sent is not None:
        return _in_one_pass(windows, sent)
    if sent is not None and parallel == "stream":

        def answer(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                rows = []
                for sid, n, start, text in zip(b.stream_id, b.n_seen, b.win_start, b.win_text, strict=True):
                    find = finder(text, start, method, rule, ancestor, children)
                    rows += [(sid, q, n, off) for q, p in sent if len(p) <= len(text) for off in find(p)]
                yield _emit(rows)

        return windows.select("stream_id", "n_seen", "win_start", "win_text").mapInPandas(answer, MATCHES)
    # Queries of their own for each stream, or too many to send: pairs meet in a join.
    if queries.where("stream_id is null").limit(1).count() or parallel == "query":
        pairs = gram_pairs(windows, queries)
    else:
        pairs = windows.join(queries.where("pattern is not null").select("stream_id", "query_id", "pattern"), "stream_id").where("length(pattern) <= length(win_text)")

    return _paired(pairs, method, rule, ancestor, children)


def _in_one_pass(windows: DataFrame, sent: list[tuple[str, str]]) -> DataFrame:
    ids: dict[str, list[str]] = {}
    for q, p in sent:
        ids.setdefault(p, []).append(q)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        find = matcher(list(ids))
        for b in batches:
            rows = [(sid, q, n, start + i) for sid, n, start, text in zip(b.stream_id, b.n_seen, b.win_start, b.win_text, strict=True) for p, i in find(text) for q in ids[p]]
            yield _emit(rows)

    return windows.select("stream_id", "n_seen", "win_start", "win_text").mapInPandas(run, MATCHES)


def _paired(pairs: DataFrame, method: str, rule: str, ancestor: str, children: str) -> DataFrame:
    """Windows joined with their queries; rows of one window stand together."""

    def paired(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        last, find = None, None
        for b in batches:
            rows = []
            for sid, n, start, text, q, p in zip(b.stream_id, b.n_seen, b.win_start, b.win_text, b.query_id, b.pattern, strict=True):
                if last != (sid, n):
                    last, find = (sid, n), finder(text, start, method, rule, ancestor, children)
                rows += [(sid, q, n, off) for off in find(p)]
            yield _emit(rows)

    ordered = pairs.select("stream_id", "n_seen", "win_start", "win_text", "query_id", "pattern").repartition("stream_id", "n_seen").sortWithinPartitions("stream_id", "n_seen")
    return ordered.mapInPandas(paired, MATCHES)


def locate_at(texts: DataFrame, queries: DataFrame, capacity: int, method: str = "index", rule: str = "project") -> DataFrame:
    """(stream_id, text), QUERIES with stream and ``at_seq`` -> MATCHES as of that many symbols."""
    asked = queries.where("at_seq is not null and length(pattern) > 0")
    rows = texts.join(asked, "stream_id").where(F.col("at_seq").between(1, F.length("text")))
    window = F.expr(f"substring(text, cast(greatest(at_seq - {capacity}, 0) as int) + 1, cast(least(at_seq, {capacity}) as int))")
    rows = rows.select("stream_id", F.col("at_seq").alias("n_seen"), F.greatest(F.col("at_seq") - capacity, F.lit(0)).alias("win_start"), window.alias("win_text"), "query_id", "pattern")
    return _paired(rows.where("length(pattern) <= length(win_text)"), method, rule, "order_list", "hash")


def _by_segment(windows: DataFrame, queries: DataFrame, sent: list | None) -> DataFrame:
    from winsub.operators.segments import locate_segmented, seal_segments
    from winsub.sources.adapters import chunks

    if sent is None:
        raise ValueError("segments take a bounded set of queries for all streams")
    longest = max((len(p) for _, p in sent), default=1)
    cut = chunks(windows.select("stream_id", F.col("win_text").alias("text")), max(1 << 16, longest))
    found = locate_segmented(seal_segments(cut, longest), queries, longest).drop("n_seen")
    return found.join(windows.select("stream_id", "n_seen", "win_start"), "stream_id").select("stream_id", "query_id", "n_seen", (F.col("win_start") + F.col("off")).alias("off"))


def _declared(windows: DataFrame, queries: DataFrame, method: str, sent: list | None) -> DataFrame:
    q = queries.where("pattern is not null").select("query_id", F.col("stream_id").alias("only"), "pattern")
    if sent is not None:
        pairs = windows.join(F.broadcast(q), F.expr("(only is null or only = stream_id) and contains(win_text, pattern)"))
    else:
        pairs = gram_pairs(windows, queries)
    if method == "sql":
        at = F.expr("filter(sequence(0, length(win_text) - length(pattern)), i -> substring(win_text, i + 1, length(pattern)) = pattern)")
    else:
        at = positions()
    return pairs.select("stream_id", "query_id", "n_seen", "win_start", F.explode(at).alias("i")).select("stream_id", "query_id", "n_seen", (F.col("win_start") + F.col("i")).cast("long").alias("off"))


def count_matches(windows: DataFrame, queries: DataFrame, zeros: bool = True, **options) -> DataFrame:
    """(stream_id, query_id, cnt); with ``zeros`` a row for every window and query, for query sets that can be sent."""
    found = locate(windows, queries, **options).groupBy("stream_id", "query_id").agg(F.count(F.lit(1)).alias("cnt"))
    if not zeros:
        return found
    if sendable(queries) is None:
        own = queries.where("stream_id is not null").select("stream_id", "query_id")
        if queries.where("stream_id is null").limit(1).count():
            raise ValueError("too many queries for a row for every window and query: ask without zeros")
        every = windows.select("stream_id").join(own, "stream_id")
    else:
        every = windows.select("stream_id").join(F.broadcast(queries.select("query_id")))
    return every.join(found, ["stream_id", "query_id"], "left").select("stream_id", "query_id", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def exists_match(windows: DataFrame, queries: DataFrame, **options) -> DataFrame:
    return count_matches(windows, queries, **options).select("stream_id", "query_id", (F.col("cnt") > 0).alias("flag"))


def first_last(windows: DataFrame, queries: DataFrame, **options) -> DataFrame:
    return locate(windows, queries, **options).groupBy("stream_id", "query_id").agg(F.min("off").alias("lo"), F.max("off").alias("hi"))


def locate_array(windows: DataFrame, queries: DataFrame, **options) -> DataFrame:
    return locate(windows, queries, **options).groupBy("stream_id", "query_id").agg(F.array_sort(F.collect_list("off")).alias("offs"))
