"""Work, space and accuracy of the index and of the baselines, counted in elementary steps."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winsub.kernel.scan import kmp_find, native_find, skip_find
from winsub.kernel.static_index import BackwardSearch, SuffixArray
from winsub.kernel.window_index import Steps, WindowIndex
from winsub.model import names
from winsub.operators.tail import occ_split, tail_table

QUERY_WORK = "stream_id string, query_id string, m bigint, occ bigint, compares bigint, nodes bigint, ancestor_tests bigint, progressions bigint, steps bigint, ratio double"
UPDATE_WORK = "stream_id string, pushes bigint, grows bigint, leaves_made bigint, splits bigint, link_walks bigint, skip_walks bigint, drops bigint, splices bigint, recycles bigint, order_moves bigint, steps bigint, max_push_steps bigint"
FOOTPRINT = "stream_id string, w bigint, tree_nodes bigint, link_nodes bigint, ancestor_words bigint, snapshot_bytes bigint, per_symbol double"


def query_work(windows: DataFrame, patterns: list[str], rule: str = "project") -> DataFrame:
    """Steps of every query; ``ratio`` is steps / (m + occ + 1)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.win_text, strict=True):
                index = WindowIndex(max(1, len(text))).extend(text)
                for p in patterns:
                    work = Steps()
                    occ, m = len(index.locate(p, rule, work=work, ordered=False)), len(p)
                    out.append((sid, p, m, occ, work["compares"], work["nodes"], work["ancestor_tests"], work["progressions"], work.total(), work.total() / (m + occ + 1)))
            yield pd.DataFrame(out, columns=names(QUERY_WORK))

    return windows.select("stream_id", "win_text").mapInPandas(run, QUERY_WORK)


def update_work(rows: DataFrame, capacity: int) -> DataFrame:
    """Steps of feeding each text to a window."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.text, strict=True):
                index = WindowIndex(capacity).extend(text)
                s = index.steps
                out.append((sid, s["pushes"], s["pushes"] - s["leaves_made"], s["leaves_made"], s["splits"], s["link_walks"], s["skip_walks"], s["drops"], s["splices"], s["recycles"], s["order_moves"], s.total(), index.max_push))
            yield pd.DataFrame(out, columns=names(UPDATE_WORK))

    return rows.select("stream_id", "text").mapInPandas(run, UPDATE_WORK)


def footprint(windows: DataFrame, ancestor: str = "order_list") -> DataFrame:
    """Nodes, words and bytes of each window's index."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.win_text, strict=True):
                f = WindowIndex(max(1, len(text)), ancestor=ancestor).extend(text).footprint()
                out.append((sid, len(text), f["tree_nodes"], f["link_nodes"], f["ancestor_words"], f["snapshot_bytes"], f["snapshot_bytes"] / max(1, len(text))))
            yield pd.DataFrame(out, columns=names(FOOTPRINT))

    return windows.select("stream_id", "win_text").mapInPandas(run, FOOTPRINT)


def tail_stats(windows: DataFrame) -> DataFrame:
    return tail_table(windows).select("stream_id", "tail_start", "tail_len", "kind", "twin", "period")


def missing_leaves(windows: DataFrame) -> DataFrame:
    """(stream_id, missing, tail_len): suffixes without a leaf, counted in the index."""
    schema = "stream_id string, missing bigint, tail_len bigint"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            made = [(sid, WindowIndex(max(1, len(t))).extend(t)) for sid, t in zip(b.stream_id, b.win_text, strict=True)]
            yield pd.DataFrame([(sid, x.size - len(x.leaf_at), x.tail_len) for sid, x in made], columns=names(schema))

    return windows.select("stream_id", "win_text").mapInPandas(run, schema)


def alphabet_factor(windows: DataFrame, patterns: list[str]) -> DataFrame:
    """(stream_id, sigma, children, compares): child look-ups by container."""
    schema = "stream_id string, sigma bigint, children string, compares bigint"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.win_text, strict=True):
                for kind in ("hash", "sorted", "dense"):
                    index = WindowIndex(max(1, len(text)), children=kind).extend(text)
                    for p in patterns:
                        index.locate(p)
                    out.append((sid, len(set(text)), kind, index.compares.n))
            yield pd.DataFrame(out, columns=names(schema))

    return windows.select("stream_id", "win_text").mapInPandas(run, schema)


def exactness(found: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """(precision, recall, duplicates) of one set of matches against another."""
    a = found.groupBy(*keys).agg(F.count(F.lit(1)).alias("times"))
    met = a.join(truth.select(*keys).distinct().withColumn("true", F.lit(1)), keys, "full_outer")
    hit = F.sum(F.expr("cast(times is not null and true is not null as int)"))
    ratio = lambda of: F.coalesce(hit / F.sum(F.expr(f"cast({of} is not null as int)")), F.lit(1.0))
    return met.agg(ratio("times").alias("precision"), ratio("true").alias("recall"), F.coalesce(F.sum(F.col("times") - 1), F.lit(0)).alias("duplicates"))


def steps_by_method(text: str, pattern: str, w: int) -> list[tuple[str, int]]:
    """(method, steps) of one query over the last ``w`` symbols of a text."""
    return steps_by_pattern(text, [pattern], w)[0]


def steps_by_pattern(text: str, patterns: list[str], w: int) -> list[list[tuple[str, int]]]:
    """(method, steps) of each pattern's query; what the window alone determines is built once."""
    window = text[-w:]
    index = WindowIndex(w).extend(window)
    end = index.finalised().steps.total() - index.steps.total()
    # Building: a sort of w suffixes, and for backward search the marks.
    sort = w * max(1, w.bit_length())
    array = SuffixArray(window)
    backward, out = BackwardSearch(window, order=array.order), []
    for p in patterns:
        work = Steps()
        index.locate(p, work=work, ordered=False)
        base, found, back = max(1, work.total()), array.find(p)[1], backward.find(p)[1]
        out.append(
            [
                ("index", base),
                ("kmp", kmp_find(window, p)[1]),
                ("boyer_moore", skip_find(window, p)[1]),
                ("finalise", base + end),
                ("suffix_array", found),
                ("suffix_array_built", found + sort),
                ("static_bwt", back),
                ("static_bwt_built", back + sort + w),
            ]
        )
    return out


def work_vs_baseline(windows: DataFrame, patterns: list[str], sizes: list[int]) -> DataFrame:
    """(pattern, method, w, steps, ratio): steps of every method over growing windows, summed over
    the streams that have so many symbols, and as a multiple of the index's."""
    schema = "pattern string, method string, w bigint, steps bigint, base bigint"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for text in b.win_text:
                for w in (w for w in sizes if w <= len(text)):
                    for p, found in zip(patterns, steps_by_pattern(text, patterns, w), strict=True):
                        out += [(p, method, w, steps, found[0][1]) for method, steps in found]
            yield pd.DataFrame(out, columns=names(schema))

    summed = windows.select("win_text").mapInPandas(run, schema).groupBy("pattern", "method", "w").agg(F.sum("steps").alias("steps"), F.sum("base").alias("base"))
    return summed.select("pattern", "method", "w", "steps", (F.col("steps") / F.col("base")).alias("ratio"))


CLOCK = "stream_id string, w bigint, pushes_per_sec double, batch_sec double, native_sec double, text_bytes bigint, tree_bytes bigint"


def wall_clock(windows: DataFrame, patterns: list[str], repeats: int = 3) -> DataFrame:
    """Of each window: pushes a second, median seconds of all patterns by the index and by a native
    scan, and bytes of state as a text and as a tree."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for sid, text in zip(b.stream_id, b.win_text, strict=True):
                began = time.perf_counter()
                index = WindowIndex(max(1, len(text))).extend(text)
                rate = len(text) / max(1e-9, time.perf_counter() - began)
                _, indexed, _, _ = timing("index", lambda i=index: sum(len(i.locate(p, ordered=False)) for p in patterns), repeats)
                _, scanned, _, _ = timing("native", lambda t=text: sum(len(native_find(t, p)[0]) for p in patterns), repeats)
                out.append((sid, len(text), rate, indexed, scanned, len(text.encode()), len(index.snapshot())))
            yield pd.DataFrame(out, columns=names(CLOCK))

    return windows.select("stream_id", "win_text").mapInPandas(run, CLOCK)


def timing(label: str, run: Callable[[], int], repeats: int = 3) -> tuple[str, float, float, int]:
    """(label, median seconds, least seconds, rows)."""
    took, rows = [], 0
    for _ in range(repeats):
        began = time.perf_counter()
        rows = run()
        took.append(time.perf_counter() - began)
    return label, statistics.median(took), min(took), rows


__all__ = ["alphabet_factor", "exactness", "footprint", "missing_leaves", "occ_split", "query_work", "tail_stats", "timing", "steps_by_method", "steps_by_pattern", "update_work", "wall_clock", "work_vs_baseline"]
