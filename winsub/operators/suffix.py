"""The window tree as relations: suffix order, common prefixes, nodes, links, last column."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from winsub.operators.staging import staged


#: Symbols that a window may have whose substrings are all formed.
SMALL = 64


def _symbols(windows: DataFrame) -> DataFrame:
    at = F.posexplode(F.expr("transform(sequence(1, length(win_text)), i -> substring(win_text, i, 1))")).alias("i", "sym")
    rows = windows.where("length(win_text) > 0").select("stream_id", "win_start", at)
    return rows.select("stream_id", (F.col("win_start") + F.col("i")).alias("off"), "sym")


def suffix_order(windows: DataFrame) -> DataFrame:
    """(stream_id, off, rank): order of suffixes by prefix doubling, one sort a round and stream.

    A suffix that ends sorts before one that goes on.  The loop ends when every stream's
    ranks are distinct; what decides that is one row.
    """
    stream = Window.partitionBy("stream_id")
    ranked = _symbols(windows).select("stream_id", "off", F.dense_rank().over(stream.orderBy("sym")).cast("long").alias("rank"))
    width, rounds = 1, 0
    while True:
        ranked = staged(ranked, f"ranks{rounds}")
        left = ranked.groupBy("stream_id").agg((F.max("rank") < F.count(F.lit(1))).alias("open"), F.count(F.lit(1)).alias("n"))
        state = left.agg(F.max("open").alias("open"), F.max("n").alias("n")).first()
        if not state["open"] or width >= state["n"]:
            return ranked
        second = F.coalesce(F.lead("rank", width).over(stream.orderBy("off")), F.lit(0)).alias("second")
        ranked = ranked.select("stream_id", "off", "rank", second)
        ranked = ranked.select("stream_id", "off", F.dense_rank().over(stream.orderBy("rank", "second")).cast("long").alias("rank"))
        width, rounds = 2 * width, rounds + 1


#: Longest common prefix of strings x and y, by bisection.
_COMMON = """aggregate(sequence(1, 32), named_struct('lo', 0, 'hi', least(length(x), length(y))),
  (a, i) -> if(a.lo >= a.hi, a, if(left(x, div(a.lo + a.hi + 1, 2)) = left(y, div(a.lo + a.hi + 1, 2)),
    named_struct('lo', div(a.lo + a.hi + 1, 2), 'hi', a.hi), named_struct('lo', a.lo, 'hi', div(a.lo + a.hi + 1, 2) - 1))), a -> a.lo)""".replace("div(a.lo + a.hi + 1, 2)", "cast(floor((a.lo + a.hi + 1) / 2) as int)")


def lcp_table(windows: DataFrame) -> DataFrame:
    """(stream_id, off, rank, lcp): common prefix with the next suffix in order (0 at the last)."""
    order = suffix_order(windows).join(windows.select("stream_id", "win_start", "win_text"), "stream_id")
    after = F.lead("off").over(Window.partitionBy("stream_id").orderBy("rank"))
    pairs = order.withColumn("after", after)
    pairs = pairs.withColumn("x", F.expr("substring(win_text, cast(off - win_start as int) + 1)")).withColumn("y", F.expr("coalesce(substring(win_text, cast(after - win_start as int) + 1), '')"))
    return pairs.select("stream_id", "off", "rank", F.expr(_COMMON).cast("long").alias("lcp"))


def longest_repeat(windows: DataFrame) -> DataFrame:
    """(stream_id, len): the longest substring that occurs twice."""
    return lcp_table(windows).groupBy("stream_id").agg(F.max("lcp").alias("len"))


def tree_nodes(windows: DataFrame, tails: DataFrame) -> DataFrame:
    """(stream_id, node_str, depth, link_str, n_children) of internal nodes and the root.

    All substrings that begin before the tail are formed, so windows must be small: a window of
    more than ``SMALL`` symbols ends the job.
    """
    small = F.when(F.length("win_text") <= SMALL, F.col("win_text")).otherwise(F.raise_error(F.lit(f"tree_nodes takes windows of at most {SMALL} symbols")))
    rows = windows.withColumn("win_text", small).join(tails.select("stream_id", "tail_len"), "stream_id")
    starts = rows.select("stream_id", "win_text", F.explode(F.expr("sequence(1, length(win_text) - cast(tail_len as int))")).alias("p"))
    strings = starts.select("stream_id", "win_text", "p", F.explode(F.expr("sequence(0, length(win_text) - p)")).alias("d"))
    strings = strings.select("stream_id", F.expr("substring(win_text, p, d)").alias("node_str"), F.expr("substring(win_text, p + d, 1)").alias("next"))
    nodes = strings.groupBy("stream_id", "node_str").agg(F.countDistinct("next").alias("n_children")).where("n_children >= 2 or node_str = ''")
    link = F.expr("if(node_str = '', null, substring(node_str, 2))")
    return nodes.select("stream_id", "node_str", F.length("node_str").cast("long").alias("depth"), link.alias("link_str"), "n_children")


def link_edges(nodes: DataFrame) -> DataFrame:
    """(stream_id, node_str, link_str) of links whose target is a node (all are)."""
    targets = nodes.select("stream_id", F.col("node_str").alias("link_str"))
    return nodes.where("node_str <> ''").select("stream_id", "node_str", "link_str").join(targets, ["stream_id", "link_str"]).select("stream_id", "node_str", "link_str")


def link_intervals(nodes: DataFrame) -> DataFrame:
    """(stream_id, node_str, pre, post): a node is an ancestor if its interval contains another's.

    Links drop the first symbol, so the link tree's order is that of the reversed strings:
    a node's descendants are those whose reversed string starts with its own.
    """
    rows = nodes.select("stream_id", "node_str", F.reverse("node_str").alias("back"))
    order = Window.partitionBy("stream_id").orderBy("back")
    ranked = rows.withColumn("pre", F.row_number().over(order).cast("long"))
    below = ranked.alias("a").join(ranked.alias("b"), F.expr("a.stream_id = b.stream_id and startswith(b.back, a.back)"))
    return below.groupBy(F.col("a.stream_id").alias("stream_id"), F.col("a.node_str").alias("node_str")).agg(F.min("b.pre").alias("pre"), F.max("b.pre").alias("post"))


def bwt_table(windows: DataFrame) -> DataFrame:
    """(stream_id, rank, off, last): the symbol before each suffix; null before the first."""
    order = suffix_order(windows).join(windows.select("stream_id", "win_start", "win_text"), "stream_id")
    return order.select("stream_id", "rank", "off", F.expr("if(off = win_start, null, substring(win_text, cast(off - win_start as int), 1))").alias("last"))
