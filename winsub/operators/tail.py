"""The tail of a window and its matches as JVM expressions: no shuffle, no Python."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winsub.operators.locate import positions
from winsub.plans.planner import gram_pairs, sendable

#: Longest k so that the last k symbols occur earlier: bisection, as that is monotone in k.
_LONGEST = """aggregate(sequence(1, 32), named_struct('lo', 0, 'hi', greatest(length(win_text) - 1, 0)),
  (a, i) -> if(a.lo >= a.hi, a, if(instr(left(win_text, length(win_text) - 1), right(win_text, MID)) > 0,
    named_struct('lo', MID, 'hi', a.hi), named_struct('lo', a.lo, 'hi', MID - 1))), a -> a.lo)""".replace("MID", "cast(floor((a.lo + a.hi + 1) / 2) as int)")


def tail_table(windows: DataFrame) -> DataFrame:
    """WINDOWS -> TAILS (with win_start and win_text kept)."""
    rows = windows.where("win_text is not null").withColumn("b", F.expr(_LONGEST))
    rows = rows.withColumn("one", F.expr("if(b = 0, 0, instr(win_text, right(win_text, b)))"))
    rows = rows.withColumn("two", F.expr("if(b = 0, 0, locate(right(win_text, b), win_text, one + 1))"))
    leaf = F.expr("b > 0 and two = length(win_text) - b + 1")
    start = F.col("n_seen") - F.col("b")
    twin = F.when(leaf, F.col("win_start") + F.col("one") - 1)
    return rows.select(
        "stream_id", "n_seen", "win_start", "win_text",
        start.alias("tail_start"),
        F.col("b").cast("long").alias("tail_len"),
        F.when(F.col("b") == 0, "root").when(leaf, "leaf").otherwise("internal").alias("kind"),
        twin.alias("twin"),
        (start - twin).alias("period"),
    )


def period_table(windows: DataFrame) -> DataFrame:
    """(stream_id, n_seen, twin, period, period_text) of tails with a single twin."""
    t = tail_table(windows).where("kind = 'leaf'")
    return t.select("stream_id", "n_seen", "twin", "period", F.expr("substring(win_text, cast(twin - win_start as int) + 1, cast(period as int))").alias("period_text"), "tail_len")


def predict_next(windows: DataFrame) -> DataFrame:
    """(stream_id, n_seen, twin, period, expected): the symbol that extends the tail."""
    return period_table(windows).select("stream_id", "n_seen", "twin", "period", F.expr("substring(period_text, cast(pmod(tail_len, period) as int) + 1, 1)").alias("expected"))


def _pairs(tails: DataFrame, queries: DataFrame) -> DataFrame:
    """Windows with the queries they contain: sent if their size allows it, else by a q-gram."""
    queries = queries.where("stream_id is null")
    if sendable(queries) is None:
        return gram_pairs(tails, queries)
    return tails.join(F.broadcast(queries.select("query_id", "pattern")), F.expr("contains(win_text, pattern)"))


def leaf_hits(tails: DataFrame, queries: DataFrame) -> DataFrame:
    """Matches that start before the tail."""
    hits = _pairs(tails, queries).select("stream_id", "query_id", "n_seen", "tail_start", "win_start", F.explode(positions()).alias("i"))
    return hits.select("stream_id", "query_id", "n_seen", (F.col("win_start") + F.col("i")).alias("off"), "tail_start").where("off < tail_start").drop("tail_start")


def tail_hits(tails: DataFrame, queries: DataFrame) -> DataFrame:
    """Matches inside the tail: by its period where it has a twin, else in the tail's own text."""
    rows = _pairs(tails, queries).where("length(pattern) <= tail_len")
    at_leaf = rows.where("kind = 'leaf'").select("*", F.explode(positions()).alias("i"))
    z = F.col("win_start") + F.col("i")
    stop = F.expr("n_seen - length(pattern)")
    steps = at_leaf.withColumn("z", z).where("z >= twin and z < tail_start").withColumn("stop", stop).where("z + period <= stop")
    steps = steps.select("stream_id", "query_id", "n_seen", F.explode(F.expr("sequence(z + period, stop, period)")).alias("off"))
    inside = rows.where("kind = 'internal'").withColumn("tail", F.expr("right(win_text, cast(tail_len as int))")).where("contains(tail, pattern)")
    inside = inside.select("stream_id", "query_id", "n_seen", "tail_start", F.explode(positions("tail")).alias("i"))
    return steps.unionByName(inside.select("stream_id", "query_id", "n_seen", (F.col("tail_start") + F.col("i")).alias("off")))


def occ_split(windows: DataFrame, queries: DataFrame) -> DataFrame:
    """(stream_id, query_id, occ_leaf, occ_tail), streams and queries with a match."""
    t = tail_table(windows)
    rows = leaf_hits(t, queries).withColumn("leaf", F.lit(1)).unionByName(tail_hits(t, queries).withColumn("leaf", F.lit(0)))
    return rows.groupBy("stream_id", "query_id").agg(F.sum("leaf").alias("occ_leaf"), F.sum(1 - F.col("leaf")).alias("occ_tail"))


def tail_case_split(windows: DataFrame, queries: DataFrame) -> DataFrame:
    """(case, cnt): how often each way of finding tail matches is taken (for queries that can be sent)."""
    if sendable(queries.where("stream_id is null")) is None:
        raise ValueError("too many queries: every window counts with each of them")
    q = F.broadcast(queries.where("stream_id is null").select("pattern"))
    rows = tail_table(windows).join(q, F.expr("length(pattern) <= length(win_text)"))
    case = F.expr("case when length(pattern) > tail_len then 'shorter' when length(pattern) = tail_len then 'equal' when kind = 'internal' then 'linked' when period <= length(pattern) then 'period_short' else 'period_long' end")
    return rows.groupBy(case.alias("case")).agg(F.count(F.lit(1)).alias("cnt"))
