"""Named workloads: each a query over the given tables and, where SQL can say it, its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winsub.kernel.window_index import WindowIndex
from winsub.operators import measures
from winsub.operators.features import qgram_features
from winsub.operators.locate import count_matches, exists_match, first_last, locate, locate_at
from winsub.operators.replay import evict_effect, replay_matches, replay_tails
from winsub.operators.codes import locate_codes
from winsub.operators.segments import expire_segments, locate_segmented, read_index, seal_segments, write_index
from winsub.operators.staging import staged_folder
from winsub.operators.suffix import bwt_table, lcp_table, link_edges, link_intervals, longest_repeat, suffix_order, tree_nodes
from winsub.operators.tail import leaf_hits, occ_split, period_table, predict_next, tail_case_split, tail_hits, tail_table
from winsub.operators.windows import make_queries, queries_from, window_at
from winsub.sources.adapters import FAMILIES, WHOLE, chunks, encode_symbols, family, family_symbols, family_window, symbol_chunks, symbols
from winsub.sources.readers import load, stream_table
from winsub.streaming.live import live_locate, locate_all, standing_match, standing_match_batch, state_store, tagged

Run = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Run] = {}
ORACLES: dict[str, str] = {}

# -- SQL pieces -----------------------------------------------------------------------------

STREAMS = {
    "ev_user": "SELECT user_id AS k, string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS t FROM events GROUP BY 1",
    "ev_all": "SELECT 0 AS k, string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS t FROM events",
    "ord_cust": "SELECT o_custkey AS k, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey) AS t FROM orders GROUP BY 1",
    "ord_prio": "SELECT o_custkey AS k, string_agg(left(o_orderpriority, 1), '' ORDER BY o_orderdate, o_orderkey) AS t FROM orders GROUP BY 1",
    "li_part": "SELECT l_partkey AS k, string_agg(l_returnflag, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_returnflag) AS t FROM lineitem GROUP BY 1",
    "conv": "SELECT conv_id AS k, string_agg(text, chr(10) ORDER BY turn, text) AS t FROM conversations GROUP BY 1",
    "doc": "SELECT doc_id AS k, text AS t FROM documents WHERE text IS NOT NULL",
    "page": "SELECT page_id AS k, html AS t FROM pages WHERE html IS NOT NULL",
    "bench": "SELECT item_id AS k, text AS t FROM benchmark WHERE text IS NOT NULL",
    "part_name": "SELECT p_partkey AS k, p_name AS t FROM part",
    "emb_code": "SELECT vec_id AS k, array_to_string(list_transform(embedding, lambda x: CASE WHEN x >= 0 THEN '+' ELSE '-' END), '') AS t FROM embeddings",
}
TAIL = """tl AS (SELECT k, n, w, coalesce(max(j), 0) AS b FROM (SELECT k, n, w, unnest(range(0, length(w))) AS j FROM wn)
  WHERE j = 0 OR strpos(left(w, length(w) - 1), right(w, j)) > 0 GROUP BY k, n, w)"""
OCC = """oc AS (SELECT k, n, w, b, list_filter(range(0, length(w) - b), lambda i: b > 0 AND substr(w, i + 1, b) = right(w, b)) AS o FROM tl)"""
NODES = """st AS (SELECT k, w, b, unnest(range(0, length(w) - b)) AS p FROM tl),
ex AS (SELECT k, w, p, unnest(range(0, length(w) - p)) AS d FROM st),
nd AS (SELECT k, substr(w, p + 1, d) AS node_str, count(DISTINCT substr(w, p + d + 1, 1)) AS kids FROM ex GROUP BY 1, 2
  HAVING count(DISTINCT substr(w, p + d + 1, 1)) >= 2 OR substr(w, p + 1, d) = '')"""


def quoted(p: str) -> str:
    return "'" + p.replace("'", "''").replace("\n", "' || chr(10) || '") + "'"


def base(name: str, capacity: int, *more: str) -> str:
    window = f"wn AS (SELECT k, length(t) AS n, right(t, {capacity}) AS w FROM s)"
    return "WITH " + ", ".join([f"s AS ({STREAMS[name]})", window, *more]) + " "


def values(patterns: list[str]) -> str:
    return "q(pattern) AS (VALUES " + ", ".join(f"({quoted(p)})" for p in patterns) + ")"


def hits(key: str, extra: str = "") -> str:
    return f"""SELECT k AS {key}, pattern, CAST(n AS BIGINT) AS n_seen, CAST(n - length(w) + i AS BIGINT) AS off {extra} FROM
      (SELECT *, unnest(range(0, length(w) - length(pattern) + 1)) AS i FROM wn, q WHERE contains(w, pattern))
      WHERE substr(w, i + 1, length(pattern)) = pattern"""


def workload(name: str, sql: str | None = None) -> Callable[[Run], Run]:
    def add(run: Run) -> Run:
        QUERIES[name] = run
        if sql is not None:
            ORACLES[name] = sql
        return run

    return add


def key_of(name: str) -> str:
    return "stream" if name == "ev_all" else FAMILIES[name].key


def windows(spark: SparkSession, sf_dir: str, name: str, capacity: int) -> DataFrame:
    return family_window(spark, sf_dir, name, capacity)


def keyed(df: DataFrame, name: str, *columns) -> DataFrame:
    return df.select(F.col("stream_id").cast("long").alias(key_of(name)), *columns)


# -- locate ---------------------------------------------------------------------------------

EV = ["e", "ev", "vs", "ccc", "pcc", "zzz"]
LOCATE: dict[str, tuple[str, int, list[str], str]] = {
    "locate_ev_user": ("ev_user", 64, EV, "index"),
    "locate_ev_all": ("ev_all", 4096, ["e", "ev", "cse", "vspc", "escvp", "ccccce"], "index"),
    "locate_li_part": ("li_part", 32, ["A", "RN", "NNN", "ARN", "NRAN"], "index"),
    "locate_ord_cust": ("ord_cust", 16, ["O", "FF", "OFO", "P", "PO"], "index"),
    "locate_ord_prio": ("ord_prio", 16, ["1", "23", "55", "412"], "suffix_array"),
    "locate_doc_window": ("doc", 1024, [" the ", "tion", "\n"], "auto"),
    "locate_page_tags": ("page", 4096, ["<p>", "</", 'href="'], "auto"),
    "locate_conv": ("conv", 2048, ["the", ". ", "\n", "er "], "native"),
    "int_alphabet": ("emb_code", WHOLE, ["++", "-+-", "+----", "++++++"], "index"),
}


def _locate(name: str, capacity: int, patterns: list[str], method: str, **options) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = locate(windows(spark, sf_dir, name, capacity), make_queries(spark, patterns), method=method, **options)
        return keyed(found, name, F.col("query_id").alias("pattern"), "n_seen", "off")

    return run


for _name, (_f, _c, _p, _m) in LOCATE.items():
    workload(_name, base(_f, _c, values(_p)) + hits(key_of(_f)))(_locate(_f, _c, _p, _m))
for _m in ("kmp", "boyer_moore", "finalise", "static_bwt", "suffix_array", "native", "automaton", "sql", "catalyst"):
    workload(f"baseline_{_m}", base("ev_user", 64, values(EV)) + hits("user_id"))(_locate("ev_user", 64, EV, _m))
for _r in ("tail_kmp", "linked_and_period", "period_scan", "period_project"):
    _c = base("li_part", 32, values(["A", "RN", "NNN", "ARN"])) + hits("l_partkey")
    workload("baseline_tail_kmp" if _r == "tail_kmp" else f"rule_{_r}", _c)(_locate("li_part", 32, ["A", "RN", "NNN", "ARN"], "index", rule=_r))
for _a in ("jump", "lca", "interval", "chain", "fingerprint"):
    workload(f"ancestor_{_a}", base("ev_user", 64, values(EV)) + hits("user_id"))(_locate("ev_user", 64, EV, "index", ancestor=_a))
for _k in ("sorted", "dense"):
    workload(f"children_{_k}", base("ev_user", 64, values(EV)) + hits("user_id"))(_locate("ev_user", 64, EV, "index", children=_k))

# Baselines over windows of text, not of events.
DOC_PATTERNS = [" the ", "tion"]
for _m in ("index", "kmp", "boyer_moore", "finalise", "static_bwt", "suffix_array", "native", "automaton", "sql", "catalyst"):
    workload(f"baseline_doc_{_m}", base("doc", 1024, values(DOC_PATTERNS)) + hits("doc_id"))(_locate("doc", 1024, DOC_PATTERNS, _m))

LINES = "SELECT l_partkey AS k, list(l_linenumber ORDER BY l_shipdate, l_orderkey, l_linenumber) AS t FROM lineitem GROUP BY 1"
NUMBERS = [[1], [1, 2], [3, 1, 2], [9]]


@workload(
    "int_alphabet_lines",
    f"WITH s AS ({LINES}), wn AS (SELECT k, len(t) AS n, t[greatest(len(t) - 31, 1) : len(t)] AS w FROM s), q(pattern) AS (VALUES {', '.join(f'({x})' for x in NUMBERS)}) "
    "SELECT k AS l_partkey, array_to_string(pattern, ' ') AS pattern, CAST(n AS BIGINT) AS n_seen, CAST(n - len(w) + i AS BIGINT) AS off FROM (SELECT *, unnest(range(0, len(w) - len(pattern) + 1)) AS i FROM wn, q) WHERE w[i + 1 : i + len(pattern)] = pattern",
)
def int_alphabet_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Integers as symbols: a dictionary gives them codes, windows and patterns are lists of codes."""
    rows = symbols(load(spark, sf_dir, "lineitem"), "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber"], "l_linenumber")
    coded, codes = encode_symbols(rows)
    patterns = [(" ".join(map(str, p)), p) for p in NUMBERS]
    found = locate_codes(coded, codes, patterns, 32)
    return found.select(F.col("stream_id").cast("long").alias("l_partkey"), F.col("query_id").alias("pattern"), "n_seen", "off")


HISTORY = "WITH s AS ({s}), wn AS (SELECT k, i AS n, right(left(t, i), {c}) AS w FROM (SELECT k, t, unnest(range({e}, length(t) + 1, {e})) AS i FROM s))"


@workload("locate_history", HISTORY.format(s=STREAMS["ev_user"], c=16, e=10) + ", " + values(["e", "cs", "vv"]) + " " + hits("user_id"))
def locate_history(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = replay_matches(family(spark, sf_dir, "ev_user"), 16, ["e", "cs", "vv"], 10)
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "n_seen", "off")


@workload("locate_history_windows", HISTORY.format(s=STREAMS["ev_user"], c=16, e=10) + ", " + values(["e", "cs", "vv"]) + " " + hits("user_id"))
def locate_history_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = locate(window_at(family(spark, sf_dir, "ev_user"), 16, every=10), make_queries(spark, ["e", "cs", "vv"]), method="index")
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "n_seen", "off")


@workload("locate_at_seq", HISTORY.format(s=STREAMS["ev_user"], c=16, e=20) + ", " + values(["ev", "c"]) + " " + hits("user_id"))
def locate_at_seq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries that each ask for the window as of a place of their own."""
    rows = family(spark, sf_dir, "ev_user")
    at = F.explode(F.expr("sequence(20, length(text), 20)")).alias("at")
    asked = rows.where("length(text) >= 20").select("stream_id", at).select("*", F.explode(F.array(F.lit("ev"), F.lit("c"))).alias("pattern"))
    queries = asked.select(F.col("pattern").alias("query_id"), "stream_id", "pattern", F.col("at").cast("long").alias("at_seq"))
    return keyed(locate_at(rows, queries, 16), "ev_user", F.col("query_id").alias("pattern"), "n_seen", "off")


workload("locate_by_query", base("ev_user", 64, values(EV)) + hits("user_id"))(_locate("ev_user", 64, EV, "index", parallel="query"))
workload("locate_by_segment", base("conv", 2048, values(["the", ". "])) + hits("conv_id"))(_locate("conv", 2048, ["the", ". "], "auto", parallel="segment"))


@workload(
    "locate_doc_bench",
    "SELECT doc_id, item_id, CAST(i AS BIGINT) AS off FROM (SELECT d.doc_id, b.item_id, d.text AS t, b.text AS p, unnest(range(0, length(d.text) - length(b.text) + 1)) AS i "
    "FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE length(b.text) > 0) WHERE substr(t, i + 1, length(p)) = p",
)
def locate_doc_bench(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = locate(windows(spark, sf_dir, "doc", WHOLE), queries_from(load(spark, sf_dir, "benchmark"), "item_id", "text"))
    return found.select(F.col("stream_id").cast("long").alias("doc_id"), F.col("query_id").cast("long").alias("item_id"), "off")


#: Every family and its window.
WINDOWS = {"ev_user": 64, "ev_all": 4096, "li_part": 32, "ord_cust": 16, "ord_prio": 16, "conv": 2048, "doc": 1024, "page": 4096, "bench": WHOLE, "part_name": WHOLE, "emb_code": WHOLE}


def _own_queries(rows: DataFrame, pattern: str) -> DataFrame:
    """A query of its own for each stream and length ``m``."""
    return rows.select(F.col("m").cast("string").alias("query_id"), "stream_id", F.expr(pattern).alias("pattern"), F.lit(None).cast("long").alias("at_seq"))


for _f, _c in WINDOWS.items():

    def _suffix_probe(spark, sf_dir, f=_f, c=_c):
        """Patterns of their own for each stream: the window's last symbols, so the tail answers."""
        w = windows(spark, sf_dir, f, c)
        own = w.select("stream_id", "win_text", F.explode(F.sequence(F.lit(1), F.lit(4))).alias("m")).where("length(win_text) >= m")
        method = "index" if c <= 64 else "native"
        return keyed(locate(w, _own_queries(own, "right(win_text, m)"), method=method), f, F.col("query_id").cast("long").alias("m"), "off")

    workload(
        "locate_suffix_probe" if _f == "li_part" else f"locate_suffix_probe_{_f}",
        base(_f, _c)
        + f"SELECT k AS {key_of(_f)}, m, CAST(n - length(w) + i AS BIGINT) AS off FROM (SELECT *, unnest(range(0, length(w) - m + 1)) AS i FROM (SELECT *, CAST(unnest(range(1, 5)) AS BIGINT) AS m FROM wn) WHERE length(w) >= m) WHERE substr(w, CAST(i + 1 AS INT), CAST(m AS INT)) = right(w, CAST(m AS INT))",
    )(_suffix_probe)

for _f in ("ev_user", "li_part", "ord_cust", "ord_prio", "part_name"):

    def _tail_prefixes(spark, sf_dir, f=_f, c=WINDOWS[_f]):
        """Every prefix of the tail as a pattern."""
        t = tail_table(windows(spark, sf_dir, f, c))
        own = t.where("tail_len > 0").select("stream_id", "win_text", "tail_len", F.explode(F.expr("sequence(1, cast(tail_len as int))")).alias("m"))
        queries = _own_queries(own, "substring(right(win_text, cast(tail_len as int)), 1, m)")
        return keyed(locate(t.select("stream_id", "n_seen", "win_start", "win_text"), queries, method="index"), f, F.col("query_id").cast("long").alias("m"), "off")

    workload(
        f"locate_tail_prefix_{_f}",
        base(_f, WINDOWS[_f], TAIL)
        + f"SELECT k AS {key_of(_f)}, m, CAST(n - length(w) + i AS BIGINT) AS off FROM (SELECT *, unnest(range(0, length(w) - m + 1)) AS i FROM (SELECT *, CAST(unnest(range(1, b + 1)) AS BIGINT) AS m FROM tl)) WHERE substr(w, CAST(i + 1 AS INT), CAST(m AS INT)) = left(right(w, CAST(b AS INT)), CAST(m AS INT))",
    )(_tail_prefixes)


PERIODIC = "SELECT item_id * 100 + p AS k, repeat(left(text, CAST(p AS INT)), CAST(200 // p AS INT)) AS t FROM benchmark, (VALUES (1), (2), (3), (7), (20)) v(p)"


def _periodic(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = F.explode(F.array(*map(F.lit, (1, 2, 3, 7, 20)))).alias("p")
    rows = load(spark, sf_dir, "benchmark").where("text is not null").select("item_id", "text", p)
    return rows.select(F.expr("cast(item_id * 100 + p as string)").alias("stream_id"), F.expr("repeat(left(text, p), cast(floor(200 / p) as int))").alias("text"))


@workload(
    "periodic_stream",
    f"WITH s AS ({PERIODIC}) SELECT k AS item_p, left(t, 2) AS pattern, CAST(i AS BIGINT) AS off FROM (SELECT *, unnest(range(0, length(t) - 1)) AS i FROM s) WHERE substr(t, CAST(i + 1 AS INT), 2) = left(t, 2)",
)
def periodic_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = window_at(_periodic(spark, sf_dir), 200)
    q = w.select(F.lit("two").alias("query_id"), "stream_id", F.expr("left(win_text, 2)").alias("pattern"), F.lit(None).cast("long").alias("at_seq"))
    found = locate(w, q, method="index", rule="linked_and_period").join(q.select("stream_id", "pattern"), "stream_id")
    return found.select(F.col("stream_id").cast("long").alias("item_p"), "pattern", "off")


@workload(
    "fresh_symbol_flush",
    f"WITH s AS ({PERIODIC}), wn AS (SELECT k, length(t) AS n, t AS w FROM s), {TAIL} SELECT k AS item_p, CAST(b AS BIGINT) AS tail_before, CAST(0 AS BIGINT) AS tail_after FROM tl",
)
def fresh_symbol_flush(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A symbol that the window does not have empties the tail."""

    @F.pandas_udf("struct<before: bigint, after: bigint>")
    def flush(text):
        import pandas as pd

        out = []
        for t in text:
            x = WindowIndex(len(t) + 1).extend(t)
            out.append((x.tail_len, x.extend("\x01").tail_len))
        return pd.DataFrame(out, columns=["before", "after"])

    return _periodic(spark, sf_dir).select(F.col("stream_id").cast("long").alias("item_p"), flush("text").alias("f")).select("item_p", F.col("f.before").alias("tail_before"), F.col("f.after").alias("tail_after"))


# -- tail -----------------------------------------------------------------------------------

for _f, _c in WINDOWS.items():

    def _state(spark, sf_dir, f=_f, c=_c):
        t = tail_table(windows(spark, sf_dir, f, c))
        return keyed(t, f, "n_seen", "tail_start", "tail_len")

    workload(f"tail_state_{_f}", base(_f, _c, TAIL) + f"SELECT k AS {key_of(_f)}, CAST(n AS BIGINT) AS n_seen, CAST(n - b AS BIGINT) AS tail_start, CAST(b AS BIGINT) AS tail_len FROM tl")(_state)

    def _kind(spark, sf_dir, f=_f, c=_c):
        return keyed(tail_table(windows(spark, sf_dir, f, c)), f, "kind", "twin", "period")

    workload(
        f"cursor_kind_{_f}",
        base(_f, _c, TAIL, OCC)
        + f"SELECT k AS {key_of(_f)}, CASE WHEN b = 0 THEN 'root' WHEN len(o) = 1 THEN 'leaf' ELSE 'internal' END AS kind, CASE WHEN b > 0 AND len(o) = 1 THEN CAST(n - length(w) + o[1] AS BIGINT) END AS twin, CASE WHEN b > 0 AND len(o) = 1 THEN CAST(length(w) - b - o[1] AS BIGINT) END AS period FROM oc",
    )(_kind)

    def _pump(spark, sf_dir, f=_f, c=_c):
        return keyed(predict_next(windows(spark, sf_dir, f, c)), f, "twin", "period", "expected")

    workload(
        f"period_pump_{_f}",
        base(_f, _c, TAIL, OCC)
        + f"SELECT k AS {key_of(_f)}, CAST(n - length(w) + o[1] AS BIGINT) AS twin, CAST(length(w) - b - o[1] AS BIGINT) AS period, substr(w, CAST(o[1] + b + 1 AS INT), 1) AS expected FROM oc WHERE b > 0 AND len(o) = 1",
    )(_pump)


@workload("tail_history", HISTORY.format(s=STREAMS["ev_user"], c=16, e=1) + f", {TAIL} SELECT k AS user_id, CAST(n AS BIGINT) AS n_seen, CAST(b AS BIGINT) AS tail_len FROM tl")
def tail_history(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(replay_tails(family(spark, sf_dir, "ev_user"), 16), "ev_user", "n_seen", "tail_len")


@workload("tail_history_li_part", HISTORY.format(s=STREAMS["li_part"], c=32, e=1) + f", {TAIL} SELECT k AS l_partkey, CAST(n AS BIGINT) AS n_seen, CAST(b AS BIGINT) AS tail_len FROM tl")
def tail_history_li_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(replay_tails(family(spark, sf_dir, "li_part"), 32), "li_part", "n_seen", "tail_len")


SHORT = ["A", "RN", "NNN", "NRA"]


ASKED = {"li_part": SHORT, "ev_user": EV, "ord_cust": ["O", "FF", "OFO", "P"], "conv": ["the", ". "], "doc": DOC_PATTERNS}
for _f, _p in ASKED.items():

    def _cases(spark, sf_dir, f=_f, p=_p):
        return tail_case_split(windows(spark, sf_dir, f, WINDOWS[f]), make_queries(spark, p))

    workload(
        "tail_case_split" if _f == "li_part" else f"tail_case_split_{_f}",
        base(_f, WINDOWS[_f], TAIL, OCC, values(_p))
        + 'SELECT CASE WHEN length(pattern) > b THEN \'shorter\' WHEN length(pattern) = b THEN \'equal\' WHEN len(o) <> 1 THEN \'linked\' WHEN length(w) - b - o[1] <= length(pattern) THEN \'period_short\' ELSE \'period_long\' END AS "case", CAST(count(*) AS BIGINT) AS cnt FROM oc, q WHERE length(pattern) <= length(w) GROUP BY 1',
    )(_cases)

    def _split(spark, sf_dir, f=_f, p=_p):
        found = occ_split(windows(spark, sf_dir, f, WINDOWS[f]), make_queries(spark, p))
        return keyed(found, f, F.col("query_id").alias("pattern"), "occ_leaf", "occ_tail")

    workload(
        "occ_split" if _f == "li_part" else f"occ_split_{_f}",
        base(_f, WINDOWS[_f], TAIL, values(_p))
        + f"SELECT k AS {key_of(_f)}, pattern, CAST(count(*) FILTER (WHERE i < length(w) - b) AS BIGINT) AS occ_leaf, CAST(count(*) FILTER (WHERE i >= length(w) - b) AS BIGINT) AS occ_tail FROM (SELECT *, unnest(range(0, length(w) - length(pattern) + 1)) AS i FROM tl, q WHERE contains(w, pattern)) WHERE substr(w, i + 1, length(pattern)) = pattern GROUP BY 1, 2",
    )(_split)


@workload("locate_relational", base("li_part", 32, values(SHORT)) + hits("l_partkey"))
def locate_relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leaf and tail matches as relations, put together."""
    t = tail_table(windows(spark, sf_dir, "li_part", 32))
    q = make_queries(spark, SHORT)
    return keyed(leaf_hits(t, q).unionByName(tail_hits(t, q)), "li_part", F.col("query_id").alias("pattern"), "n_seen", "off")


@workload("period_text", base("ord_cust", 16, TAIL, OCC) + "SELECT k AS o_custkey, substr(w, CAST(o[1] + 1 AS INT), CAST(length(w) - b - o[1] AS INT)) AS period_text FROM oc WHERE b > 0 AND len(o) = 1")
def period_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(period_table(windows(spark, sf_dir, "ord_cust", 16)), "ord_cust", "period_text")


# -- expiry, nodes, links -------------------------------------------------------------------

_AFTER = """af AS (SELECT k, coalesce(max(j), 0) AS a FROM (SELECT k, substr(w, 2) AS v, unnest(range(0, length(w) - 1)) AS j FROM wn WHERE length(w) > 1)
  WHERE j = 0 OR strpos(left(v, length(v) - 1), right(v, j)) > 0 GROUP BY k)"""
for _f, _c in (("ev_user", 16), ("li_part", 32), ("ord_cust", 16)):

    def _effect(spark, sf_dir, f=_f, c=_c):
        return keyed(evict_effect(windows(spark, sf_dir, f, c)), f, "before", "after")

    workload(f"evict_effect_{_f}", base(_f, _c, TAIL, _AFTER) + f"SELECT k AS {key_of(_f)}, CAST(b AS BIGINT) AS before, CAST(coalesce(a, 0) AS BIGINT) AS after FROM tl LEFT JOIN af USING (k)")(_effect)


for _f, _c in (("ev_user", 32), ("li_part", 32), ("ord_cust", 16)):

    def _evicted(spark, sf_dir, f=_f, c=_c):
        return keyed(evict_effect(windows(spark, sf_dir, f, c)), f, "kids")

    workload(
        "evict_children" if _f == "ev_user" else f"evict_children_{_f}",
        base(_f, _c, TAIL, NODES) + f"SELECT k AS {key_of(_f)}, CAST(arg_max(kids, length(node_str)) AS BIGINT) AS kids FROM nd JOIN wn USING (k) WHERE starts_with(w, node_str) AND node_str <> w GROUP BY 1",
    )(_evicted)


def _nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = windows(spark, sf_dir, "ev_user", 32)
    return tree_nodes(w, tail_table(w))


@workload("node_count", base("ev_user", 32, TAIL, NODES) + "SELECT tl.k AS user_id, CAST(count(*) AS BIGINT) AS internal_nodes, CAST(any_value(length(tl.w) - b) AS BIGINT) AS leaves FROM nd JOIN tl USING (k) GROUP BY 1")
def node_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Internal nodes and leaves as the index holds them."""
    found = measures.footprint(windows(spark, sf_dir, "ev_user", 32))
    return keyed(found, "ev_user", F.col("link_nodes").alias("internal_nodes"), (F.col("tree_nodes") - F.col("link_nodes")).alias("leaves"))


@workload("tree_nodes", base("ev_user", 32, TAIL, NODES) + "SELECT k AS user_id, node_str, CAST(length(node_str) AS BIGINT) AS depth, CAST(kids AS BIGINT) AS n_children FROM nd")
def nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(_nodes(spark, sf_dir), "ev_user", "node_str", "depth", "n_children")


@workload("link_edges", base("ev_user", 32, TAIL, NODES) + "SELECT a.k AS user_id, a.node_str, b.node_str AS link_str FROM nd a JOIN nd b ON a.k = b.k AND substr(a.node_str, 2) = b.node_str WHERE a.node_str <> ''")
def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(link_edges(_nodes(spark, sf_dir)), "ev_user", "node_str", "link_str")


@workload(
    "link_intervals",
    base("ev_user", 32, TAIL, NODES, "r AS (SELECT k, node_str, reverse(node_str) AS z, row_number() OVER (PARTITION BY k ORDER BY reverse(node_str)) AS pre FROM nd)")
    + "SELECT a.k AS user_id, a.node_str, CAST(min(b.pre) AS BIGINT) AS pre, CAST(max(b.pre) AS BIGINT) AS post FROM r a JOIN r b ON a.k = b.k AND starts_with(b.z, a.z) GROUP BY 1, 2",
)
def intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(link_intervals(_nodes(spark, sf_dir)), "ev_user", "node_str", "pre", "post")


_ORDER = "so AS (SELECT k, t, off, row_number() OVER (PARTITION BY k ORDER BY substr(t, CAST(off + 1 AS INT))) AS rank FROM (SELECT k, t, unnest(range(0, length(t))) AS off FROM s))"
_LCP = "lc AS (SELECT k, off, rank, coalesce(len(list_filter(range(1, least(length(x), length(y)) + 1), lambda i: left(x, i) = left(y, i))), 0) AS lcp FROM (SELECT *, substr(t, CAST(off + 1 AS INT)) AS x, lead(substr(t, CAST(off + 1 AS INT))) OVER (PARTITION BY k ORDER BY rank) AS y FROM so))"
for _f in ("bench", "part_name"):

    def _suffixes(spark, sf_dir, f=_f):
        return keyed(suffix_order(windows(spark, sf_dir, f, WHOLE)), f, "off", "rank")

    workload(f"suffix_order_{_f}", base(_f, WHOLE, _ORDER) + f"SELECT k AS {key_of(_f)}, CAST(off AS BIGINT) AS off, CAST(rank AS BIGINT) AS rank FROM so")(_suffixes)


for _f, _c in (("part_name", WHOLE), ("bench", WHOLE), ("ev_user", 64)):

    def _lcps(spark, sf_dir, f=_f, c=_c):
        return keyed(lcp_table(windows(spark, sf_dir, f, c)), f, "rank", "lcp")

    def _repeats(spark, sf_dir, f=_f, c=_c):
        return keyed(longest_repeat(windows(spark, sf_dir, f, c)), f, "len")

    _own = f"WITH s0 AS ({STREAMS[_f]}), s AS (SELECT k, right(t, {_c}) AS t FROM s0), {_ORDER}, {_LCP} "
    _name = "" if _f == "part_name" else f"_{_f}"
    workload(f"lcp_table{_name}", _own + f"SELECT k AS {key_of(_f)}, CAST(rank AS BIGINT) AS rank, CAST(lcp AS BIGINT) AS lcp FROM lc")(_lcps)
    workload(f"longest_repeat{_name}", _own + f"SELECT k AS {key_of(_f)}, CAST(max(lcp) AS BIGINT) AS len FROM lc GROUP BY 1")(_repeats)


@workload("bwt_table", base("part_name", WHOLE, _ORDER) + "SELECT k AS p_partkey, CAST(rank AS BIGINT) AS rank, CASE WHEN off > 0 THEN substr(t, CAST(off AS INT), 1) END AS last FROM so")
def last_column(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(bwt_table(windows(spark, sf_dir, "part_name", WHOLE)), "part_name", "rank", "last")


# -- derived answers, standing queries, features, segments ----------------------------------

_COUNT = "SELECT wn.k AS {key}, q.pattern, {agg} FROM wn CROSS JOIN q LEFT JOIN (SELECT k, pattern, count(*) AS c, min(n - length(w) + i) AS lo, max(n - length(w) + i) AS hi FROM (SELECT *, unnest(range(0, length(w) - length(pattern) + 1)) AS i FROM wn, q WHERE contains(w, pattern)) WHERE substr(w, i + 1, length(pattern)) = pattern GROUP BY 1, 2) h ON h.k = wn.k AND h.pattern = q.pattern"


@workload("count_occ", base("ev_user", 64, values(EV)) + _COUNT.format(key="user_id", agg="CAST(coalesce(c, 0) AS BIGINT) AS cnt"))
def count_occ(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = count_matches(windows(spark, sf_dir, "ev_user", 64), make_queries(spark, EV), method="index")
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "cnt")


@workload("exists_occ", base("doc", WHOLE, values(["tion", "zq"])) + _COUNT.format(key="doc_id", agg="c IS NOT NULL AS flag"))
def exists_occ(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exists_match(windows(spark, sf_dir, "doc", WHOLE), make_queries(spark, ["tion", "zq"]))
    return keyed(found, "doc", F.col("query_id").alias("pattern"), "flag")


@workload("first_last_occ", base("ev_user", 64, values(EV)) + _COUNT.format(key="user_id", agg="CAST(lo AS BIGINT) AS lo, CAST(hi AS BIGINT) AS hi") + " WHERE c IS NOT NULL")
def first_last_occ(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = first_last(windows(spark, sf_dir, "ev_user", 64), make_queries(spark, EV), method="index")
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "lo", "hi")


_STAND = ["ev", "vs", "ccc", "escv"]
_EVERY = base("ev_user", WHOLE, values(_STAND)) + f"SELECT user_id, pattern, off FROM ({hits('user_id')})"


@workload("standing_match", _EVERY)
def standing(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = standing_match_batch(family(spark, sf_dir, "ev_user"), _STAND)
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "off")


def _event_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Streaming (stream_id, seq, sym) of events, in the order of time."""
    rows = stream_table(spark, sf_dir, "events")
    seq = F.unix_micros(F.col("ts").cast("timestamp")) * 1024 + F.col("event_id") % 1024
    return rows.select(F.col("user_id").cast("string").alias("stream_id"), seq.alias("seq"), F.left("event_type", F.lit(1)).alias("sym"), "event_id")


def _drained(stream: DataFrame, tag: str) -> DataFrame:
    """Run a stream over all that there is into Parquet and scan that."""
    spark = stream.sparkSession
    path = staged_folder(spark)
    with state_store(spark):
        query = stream.writeStream.format("parquet").option("path", f"{path}/{tag}").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
        query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/{tag}")


@workload("stream_standing", _EVERY)
def stream_standing(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = _drained(standing_match(_event_symbols(spark, sf_dir).drop("event_id"), _STAND), "matches")
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), "off")


_LIVE = f"""WITH e AS (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events), s AS ({STREAMS["ev_user"]}),
wn AS (SELECT k, n, right(left(t, CAST(n AS INT)), 16) AS w FROM s JOIN e ON e.user_id = s.k), {values(["e", "cs", "vv"])} {hits("user_id")}"""
for _layout in ("text+lazy", "text", "tree"):

    def _live(spark, sf_dir, layout=_layout):
        asked = tagged(_event_symbols(spark, sf_dir).withColumn("seq", F.col("seq")), ["e", "cs", "vv"], "true")
        return keyed(_drained(live_locate(asked, 16, layout), "matches"), "ev_user", F.col("query_id").alias("pattern"), "n_seen", "off")

    workload("stream_locate" if _layout == "text+lazy" else f"stream_locate_{_layout}", _LIVE)(_live)


@workload(
    "stream_locate_broadcast",
    f"""WITH s AS ({STREAMS["ev_user"]}), a AS (SELECT event_id AS at, ts FROM events WHERE event_id % 500 = 0),
c AS (SELECT user_id, at, count(*) AS n FROM events e JOIN a ON e.ts <= a.ts GROUP BY 1, 2),
wn AS (SELECT k, n, right(left(t, CAST(n AS INT)), 16) AS w FROM s JOIN c ON c.user_id = s.k), {values(["ev"])} {hits("user_id")}""",
)
def stream_locate_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries that arrive as a stream of their own and ask every registered user's window as of their place."""
    rows = stream_table(spark, sf_dir, "events", per_trigger=1 << 30)  # files have no order in time: all in one batch
    rows = rows.select("event_id", F.col("user_id").cast("string").alias("stream_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("at"), F.col("event_id").alias("tie"), F.left("event_type", F.lit(1)).alias("sym"))
    asked = rows.where("event_id % 500 = 0").select("at", F.lit("ev").alias("pattern"))
    return keyed(_drained(locate_all(rows.drop("event_id"), asked, 16), "matches"), "ev_user", F.col("query_id").alias("pattern"), "n_seen", "off")


@workload("qgram_features", "SELECT doc_id, gram, CAST(count(*) AS BIGINT) AS cnt FROM (SELECT doc_id, substr(text, CAST(i AS INT), 4) AS gram FROM (SELECT doc_id, text, unnest(range(1, length(text) - 2)) AS i FROM documents)) GROUP BY 1, 2")
def qgrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(qgram_features(family(spark, sf_dir, "doc"), 4), "doc", "gram", "cnt")


_SEG = ["e", "evs", "ccc", "cscvec"]


@workload("segmented_locate", base("ev_all", WHOLE, values(_SEG)) + f"SELECT pattern, off FROM ({hits('stream')})")
def segmented_locate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One stream of all events, cut from its symbols: it is never in one row or one task."""
    segments = seal_segments(symbol_chunks(family_symbols(spark, sf_dir, "ev_all"), 1024), 4, hot=True)
    return locate_segmented(segments, make_queries(spark, _SEG), 4).select(F.col("query_id").alias("pattern"), "off")


@workload("segmented_window", base("ev_all", 3000, values(_SEG)) + f"SELECT pattern, off FROM ({hits('stream')})")
def segmented_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only the chunks that reach into the last 3,000 symbols are sealed."""
    cut = expire_segments(symbol_chunks(family_symbols(spark, sf_dir, "ev_all"), 1024), 3000)
    return locate_segmented(seal_segments(cut, 4), make_queries(spark, _SEG), 4, capacity=3000).select(F.col("query_id").alias("pattern"), "off")


@workload("segmented_users", base("ev_user", WHOLE, values(_SEG)) + f"SELECT user_id, pattern, off FROM ({hits('user_id')})")
def segmented_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many streams of unlike lengths, short segments, patterns across seams."""
    segments = seal_segments(symbol_chunks(family_symbols(spark, sf_dir, "ev_user"), 16), 4)
    return keyed(locate_segmented(segments, make_queries(spark, _SEG), 4), "ev_user", F.col("query_id").alias("pattern"), "off")


@workload("index_store", base("ev_all", WHOLE, values(_SEG)) + f"SELECT pattern, off FROM ({hits('stream')})")
def index_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Segments written to a store and searched from there."""
    path = f"{staged_folder(spark)}/index"
    write_index(seal_segments(symbol_chunks(family_symbols(spark, sf_dir, "ev_all"), 1024), 4, hot=True), path)
    return locate_segmented(read_index(spark, path), make_queries(spark, _SEG), 4).select(F.col("query_id").alias("pattern"), "off")


_DOCSEG = ["tion", " the thing of the ", "\n"]


@workload("segmented_docs", f"WITH s AS ({STREAMS['doc']}), wn AS (SELECT k, length(t) AS n, t AS w FROM s), {values(_DOCSEG)} SELECT doc_id, pattern, off FROM ({hits('doc_id')})")
def segmented_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    segments = seal_segments(chunks(family(spark, sf_dir, "doc"), 1024), 8)
    return keyed(locate_segmented(segments, make_queries(spark, _DOCSEG), 8), "doc", F.col("query_id").alias("pattern"), "off")


# -- measures (rows only: steps are the index's own) ------------------------------------------


@workload("query_work")
def query_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.query_work(windows(spark, sf_dir, "ev_user", 64), EV, "linked_and_period")


@workload("update_work")
def update_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.update_work(family(spark, sf_dir, "ev_user"), 16)


@workload("space")
def space(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.footprint(windows(spark, sf_dir, "li_part", 32))


@workload("alphabet_factor")
def alphabet(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.alphabet_factor(windows(spark, sf_dir, "bench", WHOLE), ["the", "tion"])


@workload("missing_leaves", base("ord_cust", 16, TAIL) + "SELECT k AS o_custkey, CAST(b AS BIGINT) AS missing, CAST(b AS BIGINT) AS tail_len FROM tl")
def missing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(measures.missing_leaves(windows(spark, sf_dir, "ord_cust", 16)), "ord_cust", "missing", "tail_len")


@workload("exactness", "SELECT CAST(1.0 AS DOUBLE) AS precision, CAST(1.0 AS DOUBLE) AS recall, CAST(0 AS BIGINT) AS duplicates")
def exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, q = windows(spark, sf_dir, "li_part", 32), make_queries(spark, SHORT)
    return measures.exactness(locate(w, q, method="index"), locate(w, q, method="sql"), ["stream_id", "query_id", "off"])


@workload("work_vs_baseline")
def work_vs_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of one query by each method as the window grows, over the last symbols of the stream of all events."""
    return measures.work_vs_baseline(windows(spark, sf_dir, "ev_all", 4096), ["escvp", "ce"], [64, 256, 1024, 4096])


@workload("work_vs_baseline_doc")
def work_vs_baseline_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.work_vs_baseline(windows(spark, sf_dir, "doc", 1024), DOC_PATTERNS, [64, 1024])


@workload("wall_clock")
def wall_clock(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of a batch of queries, pushes a second, and bytes of state by layout."""
    return measures.wall_clock(windows(spark, sf_dir, "ev_all", 4096), EV)


@workload("space_bound", base("li_part", 32) + "SELECT k AS l_partkey, true AS ok FROM wn")
def space_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At most two nodes for each symbol of the window."""
    found = measures.footprint(windows(spark, sf_dir, "li_part", 32))
    return keyed(found, "li_part", (F.col("tree_nodes") <= 2 * F.col("w")).alias("ok"))


@workload("work_bound_query", base("ev_user", 64, values(EV)) + "SELECT k AS user_id, pattern, true AS ok FROM wn, q")
def work_bound_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of a query are at most 6 (m + occ + 1)."""
    found = measures.query_work(windows(spark, sf_dir, "ev_user", 64), EV)
    return keyed(found, "ev_user", F.col("query_id").alias("pattern"), (F.col("ratio") <= 6).alias("ok"))


@workload("work_bound_update", f"SELECT k AS user_id, true AS ok FROM ({STREAMS['ev_user']})")
def work_bound_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of all pushes, the order list's included, are at most 20 for each."""
    found = measures.update_work(family(spark, sf_dir, "ev_user"), 16)
    return keyed(found, "ev_user", (F.col("steps") <= 20 * F.col("pushes")).alias("ok"))
