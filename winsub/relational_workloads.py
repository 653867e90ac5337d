"""Relational operators around the matches, each as a query and as SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winsub.functions.surface import register_all
from winsub.operators.locate import count_matches, locate
from winsub.operators.tail import leaf_hits, tail_hits, tail_table
from winsub.operators.windows import make_queries, queries_from, window_at
from winsub.sources.adapters import family, symbols
from winsub.sources.readers import load
from winsub.workloads import TAIL, base, hits, values

Run = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Run] = {}
ORACLES: dict[str, str] = {}


def rel(name: str, sql: str) -> Callable[[Run], Run]:
    def add(run: Run) -> Run:
        QUERIES[f"rel_{name}"] = run
        ORACLES[f"rel_{name}"] = sql
        return run

    return add


def _ev(spark: SparkSession, sf_dir: str, patterns: list[str], capacity: int = 64) -> DataFrame:
    found = locate(window_at(family(spark, sf_dir, "ev_user"), capacity), make_queries(spark, patterns), method="catalyst")
    return found.select(F.col("stream_id").cast("long").alias("user_id"), F.col("query_id").alias("pattern"), "n_seen", "off")


def _hits(patterns: list[str], capacity: int = 64) -> str:
    return base("ev_user", capacity, values(patterns), f"h AS ({hits('user_id')})")


def _time(column: str) -> str:
    return f"strftime({column}, '%Y-%m-%d %H:%M:%S')"


def _stamp(column) -> F.Column:
    return F.date_format(column, "yyyy-MM-dd HH:mm:ss")


# -- scans and joins --------------------------------------------------------------------------


@rel("filter_project", "SELECT doc_id, n_chars FROM documents WHERE lang = 'en' AND contains(text, 'tion') AND n_chars < 2000")
def filter_project(spark, d):
    return load(spark, d, "documents").where((F.col("lang") == "en") & F.contains("text", F.lit("tion")) & (F.col("n_chars") < 2000)).select("doc_id", "n_chars")


@rel("prefix_filter", "SELECT doc_id, lang FROM documents WHERE starts_with(text, 'The')")
def prefix_filter(spark, d):
    return load(spark, d, "documents").where(F.col("text").startswith("The")).select("doc_id", "lang")


@rel("predicates", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}') AND n_chars BETWEEN 100 AND 5000 AND lang IN ('en', 'de') AND source IS NOT DISTINCT FROM source")
def predicates(spark, d):
    rows = load(spark, d, "documents").where(F.col("text").rlike("[0-9]{3}") & F.col("n_chars").between(100, 5000) & F.col("lang").isin("en", "de"))
    return rows.where(F.col("source").eqNullSafe(F.col("source"))).select("doc_id")


_TION = "c AS (SELECT doc_id, (length(text) - length(replace(text, 'tion', ''))) // 4 AS n FROM documents)"


def _tion(spark, d):
    return load(spark, d, "documents").select("doc_id", F.expr("cast((length(text) - length(replace(text, 'tion', ''))) div 4 as bigint)").alias("n"))


@rel("hash_join", f"WITH {_TION} SELECT quality, CAST(count(*) AS BIGINT) AS docs, CAST(sum(n) AS BIGINT) AS hits FROM c JOIN labels USING (doc_id) GROUP BY quality")
def hash_join(spark, d):
    return _tion(spark, d).join(load(spark, d, "labels").hint("shuffle_hash"), "doc_id").groupBy("quality").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("hits"))


@rel("merge_join", f"WITH {_TION} SELECT doc_id, CAST(n AS BIGINT) AS n, toxic FROM c JOIN labels USING (doc_id)")
def merge_join(spark, d):
    return _tion(spark, d).join(load(spark, d, "labels").hint("merge"), "doc_id").select("doc_id", "n", "toxic")


@rel("broadcast_dim", "SELECT r_name, o_orderstatus, CAST(count(*) AS BIGINT) AS cnt FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def broadcast_dim(spark, d):
    dims = load(spark, d, "nation").join(load(spark, d, "region"), F.expr("n_regionkey = r_regionkey")).select("n_nationkey", "r_name")  # at most one row a nation
    rows = load(spark, d, "orders").join(load(spark, d, "customer"), F.expr("o_custkey = c_custkey")).join(F.broadcast(dims), F.expr("c_nationkey = n_nationkey"))
    return rows.groupBy("r_name", "o_orderstatus").agg(F.count(F.lit(1)).alias("cnt"))


@rel("theta_join", base("ev_user", 64, values(["e", "ccccccccccc"])) + "SELECT k AS user_id, pattern FROM wn JOIN q ON length(pattern) <= length(w)")
def theta_join(spark, d):
    w = window_at(family(spark, d, "ev_user"), 64)
    q = make_queries(spark, ["e", "ccccccccccc"]).select("pattern")
    return w.join(F.broadcast(q), F.length("pattern") <= F.length("win_text")).select(F.col("stream_id").cast("long").alias("user_id"), "pattern")


@rel("range_join", base("ev_all", 1 << 30, values(["ccc"]), f"h AS ({hits('stream')})", "g AS (SELECT unnest(range(0, max(n) // 1024 + 1)) AS seg FROM wn)") + "SELECT CAST(seg AS BIGINT) AS seg, off FROM h JOIN g ON off >= seg * 1024 AND off < (seg + 1) * 1024")
def range_join(spark, d):
    """Offsets to the segments they lie in: ranges of the stream's whole length, met by the bins they cover."""
    w = window_at(family(spark, d, "ev_all"), 1 << 30)
    found = locate(w, make_queries(spark, ["ccc"]), method="native")
    ranges = w.select(F.explode(F.expr("sequence(0L, n_seen div 1024)")).alias("seg")).select("seg", (F.col("seg") * 1024).alias("lo"), (F.col("seg") * 1024 + 1024).alias("hi"))
    bins = ranges.withColumn("bin", F.explode(F.expr("sequence(lo div 1024, (hi - 1) div 1024)")))
    met = found.withColumn("bin", F.expr("off div 1024")).join(bins, "bin").where("off >= lo and off < hi")
    return met.select("seg", "off")


_LAST = "SELECT p.event_id, e.event_id AS error_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'error') e ON p.user_id = e.user_id AND p.ts >= e.ts"


@rel("asof_join", _LAST)
def asof_join(spark, d):
    """The latest error before each purchase: one ordered window over both kinds."""
    rows = load(spark, d, "events").where("event_type in ('purchase', 'error')")
    by = Window.partitionBy("user_id").orderBy("ts", F.expr("event_type = 'purchase'"), "event_id")
    last = F.last(F.expr("if(event_type = 'error', event_id, null)"), ignorenulls=True).over(by)
    return rows.select("event_id", "event_type", last.alias("error_id")).where("event_type = 'purchase'").select("event_id", "error_id")


@rel("interval_join", "SELECT a.event_id AS error_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def interval_join(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", "event_type", "ts", F.date_trunc("hour", "ts").alias("hour"))
    a = e.where("event_type = 'error'").withColumn("hour", F.explode(F.array(F.col("hour"), F.col("hour") + F.expr("interval 1 hour")))).alias("a")
    b = e.where("event_type = 'purchase'").alias("b")
    met = a.join(b, F.expr("a.user_id = b.user_id and a.hour = b.hour and b.ts > a.ts and b.ts <= a.ts + interval 1 hour"))
    return met.select(F.col("a.event_id").alias("error_id"), F.col("b.event_id").alias("purchase_id"))


_BENCH = "EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))"


def _with_passage(spark, d):
    """Documents that hold a passage: one pass over each text for all passages."""
    w = window_at(family(spark, d, "doc"), 1 << 30)
    found = locate(w, queries_from(load(spark, d, "benchmark"), "item_id", "text"))
    return found.select(F.col("stream_id").cast("long").alias("doc_id")).distinct()


@rel("semi", f"SELECT doc_id FROM documents d WHERE {_BENCH}")
def semi(spark, d):
    return load(spark, d, "documents").select("doc_id").join(_with_passage(spark, d), "doc_id", "left_semi")


@rel("anti", f"SELECT doc_id FROM documents d WHERE NOT {_BENCH}")
def anti(spark, d):
    return load(spark, d, "documents").select("doc_id").join(_with_passage(spark, d), "doc_id", "left_anti")


_SYMS = "y AS (SELECT l_partkey AS k, l_returnflag AS c, row_number() OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_returnflag) - 1 AS seq FROM lineitem)"


@rel("self_join", f"WITH {_SYMS} SELECT a.c || b.c AS pair, CAST(count(*) AS BIGINT) AS cnt FROM y a JOIN y b ON a.k = b.k AND b.seq = a.seq + 1 GROUP BY 1")
def self_join(spark, d):
    y = symbols(load(spark, d, "lineitem"), "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber"], "l_returnflag")
    pairs = y.alias("a").join(y.alias("b"), F.expr("a.stream_id = b.stream_id and b.seq = a.seq + 1"))
    return pairs.groupBy(F.concat("a.sym", "b.sym").alias("pair")).agg(F.count(F.lit(1)).alias("cnt"))


@rel("left_outer", base("ev_user", 64, values(["pcc", "zzz"]), f"h AS ({hits('user_id')})") + "SELECT q.pattern, CAST(count(h.off) AS BIGINT) AS cnt FROM q LEFT JOIN h ON h.pattern = q.pattern GROUP BY 1")
def left_outer(spark, d):
    q = make_queries(spark, ["pcc", "zzz"]).select("pattern")
    return q.join(_ev(spark, d, ["pcc", "zzz"]), "pattern", "left").groupBy("pattern").agg(F.count("off").alias("cnt"))


@rel("full_outer", "SELECT CASE WHEN d.doc_id IS NULL THEN 'label' WHEN l.doc_id IS NULL THEN 'document' ELSE 'both' END AS side, CAST(count(*) AS BIGINT) AS cnt FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def full_outer(spark, d):
    met = load(spark, d, "documents").select("doc_id", F.lit(1).alias("x")).join(load(spark, d, "labels").select("doc_id", F.lit(1).alias("y")), "doc_id", "full_outer")
    return met.groupBy(F.expr("case when x is null then 'label' when y is null then 'document' else 'both' end").alias("side")).agg(F.count(F.lit(1)).alias("cnt"))


# -- aggregates -------------------------------------------------------------------------------


@rel("group_having", "SELECT user_id, event_type, CAST(count(*) AS BIGINT) AS cnt FROM events GROUP BY 1, 2 HAVING count(*) >= 10")
def group_having(spark, d):
    return load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("cnt")).where("cnt >= 10")


@rel("distinct_agg", "SELECT lang, CAST(count(DISTINCT source) AS BIGINT) AS sources FROM documents WHERE contains(text, 'tion') GROUP BY 1")
def distinct_agg(spark, d):
    return load(spark, d, "documents").where(F.contains("text", F.lit("tion"))).groupBy("lang").agg(F.countDistinct("source").alias("sources"))


@rel("decimal_sum", "SELECT o_orderstatus, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM orders GROUP BY 1")
def decimal_sum(spark, d):
    return load(spark, d, "orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))


@rel("percentile", base("ev_user", 64, TAIL) + "SELECT CAST(quantile_disc(b, 0.5) AS BIGINT) AS median, CAST(max(b) AS BIGINT) AS most FROM tl")
def percentile(spark, d):
    t = tail_table(window_at(family(spark, d, "ev_user"), 64))
    return t.agg(F.expr("cast(percentile_disc(0.5) within group (order by tail_len) as bigint)").alias("median"), F.max("tail_len").alias("most"))


_ID = "CAST(count(*) AS BIGINT) AS cnt"
for _name, _sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)")):

    def _multi(spark, d, name=_name):
        grouped = getattr(load(spark, d, "lineitem"), name)("l_returnflag", "l_linestatus")
        return grouped.agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("cnt"))

    rel(_name, f"SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS gid, {_ID} FROM lineitem GROUP BY {_sql}")(_multi)


@rel("grouping_sets", f"SELECT lang, source, {_ID} FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def grouping_sets(spark, d):
    load(spark, d, "documents").select("lang", "source").createOrReplaceTempView("winsub_docs")
    return spark.sql("SELECT lang, source, count(*) AS cnt FROM winsub_docs GROUP BY GROUPING SETS ((lang), (source), ())")


@rel("pivot", "SELECT user_id, " + ", ".join(f"CAST(count(*) FILTER (WHERE event_type = '{k}') AS BIGINT) AS \"{k}\"" for k in ("error", "purchase")) + " FROM events GROUP BY 1")
def pivot(spark, d):
    wide = load(spark, d, "events").groupBy("user_id").pivot("event_type", ["error", "purchase"]).agg(F.count(F.lit(1)))
    return wide.select("user_id", *[F.coalesce(k, F.lit(0)).alias(k) for k in ("error", "purchase")])


@rel("unpivot", "SELECT s_suppkey, 'name' AS field, s_name AS value FROM supplier UNION ALL SELECT s_suppkey, 'nation', CAST(s_nationkey AS VARCHAR) FROM supplier")
def unpivot(spark, d):
    rows = load(spark, d, "supplier").select("s_suppkey", F.col("s_name").alias("name"), F.col("s_nationkey").cast("string").alias("nation"))
    return rows.unpivot("s_suppkey", ["name", "nation"], "field", "value")


# -- windows, order, sets ---------------------------------------------------------------------

_OVER = "OVER (PARTITION BY user_id ORDER BY off)"


@rel("lag_gap", _hits(["ev"]) + f"SELECT user_id, off, off - lag(off) {_OVER} AS gap FROM h")
def lag_gap(spark, d):
    return _ev(spark, d, ["ev"]).select("user_id", "off", (F.col("off") - F.lag("off").over(Window.partitionBy("user_id").orderBy("off"))).alias("gap"))


@rel("running", _hits(["ev"]) + f"SELECT user_id, off, CAST(count(*) {_OVER} AS BIGINT) AS seen FROM h")
def running(spark, d):
    return _ev(spark, d, ["ev"]).select("user_id", "off", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("off")).alias("seen"))


_RANKED = "g AS (SELECT user_id, CAST(count(*) AS BIGINT) AS cnt FROM h GROUP BY 1)"


def _per_user(spark, d):
    return _ev(spark, d, ["ev"]).groupBy("user_id").agg(F.count(F.lit(1)).alias("cnt"))


@rel("rank", base("ev_user", 64, values(["ev"]), f"h AS ({hits('user_id')})", _RANKED) + "SELECT user_id, CAST(rank() OVER (PARTITION BY user_id % 10 ORDER BY cnt DESC) AS BIGINT) AS rnk, CAST(dense_rank() OVER (PARTITION BY user_id % 10 ORDER BY cnt DESC) AS BIGINT) AS dense, CAST(row_number() OVER (PARTITION BY user_id % 10 ORDER BY cnt DESC, user_id) AS BIGINT) AS pos FROM g")
def rank(spark, d):
    by = Window.partitionBy(F.col("user_id") % 10)
    cols = [F.rank().over(by.orderBy(F.desc("cnt"))).cast("long").alias("rnk"), F.dense_rank().over(by.orderBy(F.desc("cnt"))).cast("long").alias("dense")]
    return _per_user(spark, d).select("user_id", *cols, F.row_number().over(by.orderBy(F.desc("cnt"), "user_id")).cast("long").alias("pos"))


@rel("ntile", base("ev_user", 64, values(["ev"]), f"h AS ({hits('user_id')})", _RANKED) + "SELECT user_id, CAST(ntile(4) OVER (PARTITION BY user_id % 10 ORDER BY cnt, user_id) AS BIGINT) AS q, round(percent_rank() OVER (PARTITION BY user_id % 10 ORDER BY cnt), 6) AS pr FROM g")
def ntile(spark, d):
    by = Window.partitionBy(F.col("user_id") % 10)
    return _per_user(spark, d).select("user_id", F.ntile(4).over(by.orderBy("cnt", "user_id")).cast("long").alias("q"), F.round(F.percent_rank().over(by.orderBy("cnt")), 6).alias("pr"))


@rel("range_frame", "SELECT event_id, CAST(count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS last_day FROM events")
def range_frame(spark, d):
    load(spark, d, "events").select("event_id", "user_id", "ts").createOrReplaceTempView("winsub_events")
    return spark.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS last_day FROM winsub_events")


@rel("topk", base("ev_user", 64, values(["ev"]), f"h AS ({hits('user_id')})", _RANKED) + "SELECT user_id, cnt FROM g ORDER BY cnt DESC, user_id LIMIT 10")
def topk(spark, d):
    return _per_user(spark, d).orderBy(F.desc("cnt"), "user_id").limit(10)


@rel("sort_page", base("ev_user", 64, values(["ev"]), f"h AS ({hits('user_id')})", _RANKED) + "SELECT user_id, cnt FROM g ORDER BY cnt DESC, user_id LIMIT 5 OFFSET 10")
def sort_page(spark, d):
    return _per_user(spark, d).orderBy(F.desc("cnt"), "user_id").offset(10).limit(5)


@rel("union", base("li_part", 32, values(["RN"])) + hits("l_partkey"))
def union(spark, d):
    t, q = tail_table(window_at(family(spark, d, "li_part"), 32)), make_queries(spark, ["RN"])
    found = leaf_hits(t, q).unionByName(tail_hits(t, q))
    return found.select(F.col("stream_id").cast("long").alias("l_partkey"), F.col("query_id").alias("pattern"), "n_seen", "off")


@rel("intersect", _hits(["pcc", "ccc"]) + "SELECT user_id FROM h WHERE pattern = 'pcc' INTERSECT SELECT user_id FROM h WHERE pattern = 'ccc'")
def intersect(spark, d):
    h = _ev(spark, d, ["pcc", "ccc"])
    return h.where("pattern = 'pcc'").select("user_id").intersect(h.where("pattern = 'ccc'").select("user_id"))


@rel("except", "SELECT CAST(NULL AS BIGINT) AS off WHERE false")
def except_(spark, d):
    """The index's matches without the scan's: none, duplicates counted."""
    w, q = window_at(family(spark, d, "li_part"), 32), make_queries(spark, ["RN", "A"])
    cols = ["stream_id", "query_id", "off"]
    return locate(w, q, method="index").select(cols).exceptAll(locate(w, q, method="sql").select(cols)).select("off")


@rel("sample", "SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS VARCHAR)), 1, 1) IN ('0', '1')")
def sample(spark, d):
    return load(spark, d, "documents").where(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 1).isin("0", "1")).select("doc_id")


@rel("dedup", "SELECT md5(text) AS digest, min(doc_id) AS first, CAST(count(*) AS BIGINT) AS copies FROM documents GROUP BY 1 HAVING count(*) > 1")
def dedup(spark, d):
    rows = load(spark, d, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("digest"))
    return rows.agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("copies")).where("copies > 1")


# -- scalar functions ---------------------------------------------------------------------------


@rel(
    "string_fns",
    "SELECT p_partkey, upper(p_name) AS u, reverse(p_name) AS r, replace(p_name, 'a', 'A') AS rep, lpad(p_brand, 12, '*') AS pad, split_part(p_type, ' ', 1) AS part, translate(p_name, 'aei', '123') AS tr, CAST(strpos(p_name, 'a') AS BIGINT) AS pos, left(p_name, 3) || right(p_name, 2) AS ends, md5(p_name) AS digest, CAST(levenshtein(p_name, p_brand) AS BIGINT) AS lev, CAST(ascii(p_name) AS BIGINT) AS code, repeat(left(p_name, 1), 3) AS thrice FROM part",
)
def string_fns(spark, d):
    p = load(spark, d, "part")
    return p.select(
        "p_partkey", F.upper("p_name").alias("u"), F.reverse("p_name").alias("r"), F.replace("p_name", F.lit("a"), F.lit("A")).alias("rep"), F.lpad("p_brand", 12, "*").alias("pad"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("part"),
        F.translate("p_name", "aei", "123").alias("tr"), F.instr("p_name", "a").cast("long").alias("pos"), F.concat(F.left("p_name", F.lit(3)), F.right("p_name", F.lit(2))).alias("ends"), F.md5(F.col("p_name").cast("binary")).alias("digest"),
        F.levenshtein("p_name", "p_brand").cast("long").alias("lev"), F.ascii("p_name").cast("long").alias("code"), F.repeat(F.left("p_name", F.lit(1)), 3).alias("thrice"),
    )


@rel("math_fns", "SELECT p_partkey, CAST(p_size % 7 AS BIGINT) AS m, CAST(floor(p_retailprice / 3) AS BIGINT) AS f, CAST(ceil(p_retailprice / 3) AS BIGINT) AS c, round(log2(p_size + 1), 6) AS l, CAST(greatest(p_size, 25) AS BIGINT) AS g, CAST(p_size & 5 AS BIGINT) AS a, CAST(p_size >> 2 AS BIGINT) AS s FROM part")
def math_fns(spark, d):
    e = ["p_partkey", "cast(pmod(p_size, 7) as bigint) m", "cast(floor(p_retailprice / 3) as bigint) f", "cast(ceil(p_retailprice / 3) as bigint) c", "round(log2(p_size + 1), 6) l", "cast(greatest(p_size, 25) as bigint) g", "cast(p_size & 5 as bigint) a", "cast(shiftright(p_size, 2) as bigint) s"]
    return load(spark, d, "part").selectExpr(*e)


@rel("date_fns", f"SELECT event_id, {_time('date_trunc(' + chr(39) + 'hour' + chr(39) + ', ts)')} AS hour, {_time('ts + INTERVAL 90 MINUTE')} AS later, CAST(year(ts) AS BIGINT) AS y, CAST(dayofyear(ts) AS BIGINT) AS doy FROM events")
def date_fns(spark, d):
    e = load(spark, d, "events")
    return e.select("event_id", _stamp(F.date_trunc("hour", "ts")).alias("hour"), _stamp(F.col("ts") + F.expr("make_dt_interval(0, 1, 30, 0)")).alias("later"), F.year("ts").cast("long").alias("y"), F.dayofyear("ts").cast("long").alias("doy"))


@rel("array_fns", "SELECT p_partkey, array_to_string(list_sort(list_distinct(string_split(p_name, ' '))), ',') AS words, CAST(len(string_split(p_name, ' ')) AS BIGINT) AS n, string_split(p_name, ' ')[1] AS first, array_to_string(list_transform(string_split(p_name, ' '), lambda x: left(x, 1)), '') AS initials FROM part")
def array_fns(spark, d):
    w = F.split("p_name", " ")
    cols = [F.array_join(F.array_sort(F.array_distinct(w)), ",").alias("words"), F.size(w).cast("long").alias("n"), F.try_element_at(w, F.lit(1)).alias("first")]
    return load(spark, d, "part").select("p_partkey", *cols, F.array_join(F.transform(w, lambda x: F.left(x, F.lit(1))), "").alias("initials"))


@rel("map_fns", "SELECT user_id, event_type, CAST(count(*) AS BIGINT) AS cnt FROM events GROUP BY 1, 2")
def map_fns(spark, d):
    """Counters as a map a user, and back to rows."""
    n = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    maps = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("event_type", "cnt"))


@rel("json_fns", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_fns(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@rel("hash_fns", "SELECT doc_id, sha256(text) AS sha FROM documents")
def hash_fns(spark, d):
    return load(spark, d, "documents").select("doc_id", F.sha2(F.col("text").cast("binary"), 256).alias("sha"))


@rel("struct_nested", f"WITH {_SYMS} SELECT k AS l_partkey, CAST(seq AS BIGINT) AS off, c AS sym FROM y")
def struct_nested(spark, d):
    y = symbols(load(spark, d, "lineitem"), "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber"], "l_returnflag")
    nested = y.groupBy("stream_id").agg(F.array_sort(F.collect_list(F.struct("seq", "sym"))).alias("rows"))
    return nested.select(F.col("stream_id").cast("long").alias("l_partkey"), F.inline("rows").alias("off", "sym"))


# -- time windows -------------------------------------------------------------------------------


@rel("tumbling", f"SELECT {_time('date_trunc(' + chr(39) + 'hour' + chr(39) + ', ts)')} AS begin, CAST(count(*) AS BIGINT) AS cnt FROM events GROUP BY 1")
def tumbling(spark, d):
    return load(spark, d, "events").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("cnt")).select(_stamp("w.start").alias("begin"), "cnt")


@rel("sliding", f"SELECT {_time('b')} AS begin, CAST(count(*) AS BIGINT) AS cnt FROM (SELECT time_bucket(INTERVAL 15 MINUTE, ts) - to_minutes(CAST(15 * unnest(range(0, 4)) AS INT)) AS b FROM events) GROUP BY 1")
def sliding(spark, d):
    return load(spark, d, "events").groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).agg(F.count(F.lit(1)).alias("cnt")).select(_stamp("w.start").alias("begin"), "cnt")


@rel(
    "session",
    f"SELECT user_id, {_time('min(ts)')} AS begin, CAST(count(*) AS BIGINT) AS cnt FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s",
)
def session(spark, d):
    grouped = load(spark, d, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("cnt"))
    return grouped.select("user_id", _stamp("w.start").alias("begin"), "cnt")


# -- functions, SQL -----------------------------------------------------------------------------


@rel("udf", "SELECT item_id, CAST(len(list_filter(range(0, length(text) - 1), lambda i: substr(text, i + 1, 2) = 'th')) AS BIGINT) AS n FROM benchmark")
def udf(spark, d):
    register_all(spark)
    load(spark, d, "benchmark").createOrReplaceTempView("winsub_bench")
    return spark.sql("SELECT item_id, cast(size(substr_positions(text, 'th')) as bigint) AS n FROM winsub_bench")


@rel("udf_tail", base("ev_user", 64, TAIL) + "SELECT k AS user_id, CAST(n - length(w) AS BIGINT) + CAST(length(w) - b AS BIGINT) AS tail_start, CAST(b AS BIGINT) AS tail_len, CAST(b AS BIGINT) AS by_sql FROM tl")
def udf_tail(spark, d):
    register_all(spark)
    window_at(family(spark, d, "ev_user"), 64).createOrReplaceTempView("winsub_win")
    return spark.sql("SELECT cast(stream_id as bigint) AS user_id, win_start + t.start AS tail_start, t.len AS tail_len, by_sql FROM (SELECT *, window_tail(win_text) AS t, cast(repeated_tail(win_text) as bigint) AS by_sql FROM winsub_win)")


@rel("udaf", base("ev_user", 1 << 30, TAIL) + "SELECT k AS user_id, CAST(b AS BIGINT) AS tail_len FROM tl")
def udaf(spark, d):
    register_all(spark)
    symbols(load(spark, d, "events"), "user_id", ["ts", "event_id"], "left(event_type, 1)").createOrReplaceTempView("winsub_sym")
    return spark.sql("SELECT cast(stream_id as bigint) AS user_id, tail_agg(seq, sym) AS tail_len FROM winsub_sym GROUP BY stream_id")


@rel("udtf", "SELECT item_id, CAST(i AS BIGINT) AS off FROM (SELECT item_id, text, unnest(range(0, length(text) - 1)) AS i FROM benchmark) WHERE substr(text, CAST(i + 1 AS INT), 2) = 'th'")
def udtf(spark, d):
    register_all(spark)
    load(spark, d, "benchmark").createOrReplaceTempView("winsub_bench")
    return spark.sql("SELECT item_id, off FROM winsub_bench, LATERAL locate_in(text, 'th')")


@rel("udtf_table", base("ev_user", 64, values(["ev", "ccc"])) + hits("user_id"))
def udtf_table(spark, d):
    register_all(spark)
    rows = symbols(load(spark, d, "events"), "user_id", ["ts", "event_id"], "left(event_type, 1)").select("stream_id", "seq", "sym")
    rows.createOrReplaceTempView("winsub_sym3")
    return spark.sql("SELECT cast(key as bigint) AS user_id, pattern, n_seen, off FROM locate_in_table(TABLE(winsub_sym3) PARTITION BY stream_id ORDER BY (seq, sym), 'ev|ccc', 64)")


@rel("cte_subquery", "WITH big AS (SELECT o_custkey, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1) SELECT c_custkey, n FROM customer JOIN big ON o_custkey = c_custkey WHERE n > (SELECT avg(n) FROM big) AND EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c_custkey AND o.o_orderstatus = 'P')")
def cte_subquery(spark, d):
    for name in ("orders", "customer"):
        load(spark, d, name).createOrReplaceTempView(f"winsub_{name}")
    return spark.sql("WITH big AS (SELECT o_custkey, count(*) AS n FROM winsub_orders GROUP BY 1) SELECT c_custkey, n FROM winsub_customer JOIN big ON o_custkey = c_custkey WHERE n > (SELECT avg(n) FROM big) AND EXISTS (SELECT 1 FROM winsub_orders o WHERE o.o_custkey = c_custkey AND o.o_orderstatus = 'P')")


@rel("count_zero", base("ev_user", 64, values(["zzz", "e"])) + "SELECT q.pattern, CAST(sum(CASE WHEN contains(w, q.pattern) THEN 0 ELSE 1 END) AS BIGINT) AS without FROM wn, q GROUP BY 1")
def count_zero(spark, d):
    found = count_matches(window_at(family(spark, d, "ev_user"), 64), make_queries(spark, ["zzz", "e"]), method="catalyst")
    return found.groupBy(F.col("query_id").alias("pattern")).agg(F.sum(F.expr("cast(cnt = 0 as bigint)")).alias("without"))


