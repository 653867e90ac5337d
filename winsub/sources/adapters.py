"""From tables to symbol streams and texts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winsub.operators.staging import staged
from winsub.operators.windows import window_at
from winsub.sources.readers import load

#: A window without end: texts are taken whole.
WHOLE = 1 << 30


@dataclass(frozen=True)
class Family:
    """How a table gives streams: key, order of symbols, symbol (or a whole text)."""

    table: str
    key: str
    order: tuple[str, ...] = ()
    sym: str = ""
    text: str = ""
    between: str = ""


FAMILIES = {
    "ev_user": Family("events", "user_id", ("ts", "event_id"), "left(event_type, 1)"),
    "ev_all": Family("events", "0", ("ts", "event_id"), "left(event_type, 1)"),
    "ord_cust": Family("orders", "o_custkey", ("o_orderdate", "o_orderkey"), "o_orderstatus"),
    "ord_prio": Family("orders", "o_custkey", ("o_orderdate", "o_orderkey"), "left(o_orderpriority, 1)"),
    # The symbol comes last: the columns before it have ties.
    "li_part": Family("lineitem", "l_partkey", ("l_shipdate", "l_orderkey", "l_linenumber"), "l_returnflag"),
    "conv": Family("conversations", "conv_id", ("turn",), "text", between="\n"),
    "doc": Family("documents", "doc_id", text="text"),
    "page": Family("pages", "page_id", text="html"),
    "bench": Family("benchmark", "item_id", text="text"),
    "part_name": Family("part", "p_partkey", text="p_name"),
    "emb_code": Family("embeddings", "vec_id", text="array_join(transform(embedding, x -> if(x >= 0, '+', '-')), '')"),
}


def symbols(df: DataFrame, key: str, order_by: list[str], sym: str) -> DataFrame:
    """A table's rows as SYMBOLS: ``seq`` counts a stream's symbols from 0."""
    rows = df.where(F.expr(f"{key} is not null and ({sym}) is not null"))
    order = [F.expr(x) for x in (*order_by, sym)]
    first = order_by[0] if order_by and dict(df.dtypes).get(order_by[0], "").startswith("timestamp") else "null"
    return rows.select(
        F.expr(f"cast({key} as string)").alias("stream_id"),
        (F.row_number().over(Window.partitionBy(F.expr(key)).orderBy(*order)) - 1).cast("long").alias("seq"),
        F.expr(f"cast({first} as timestamp)").alias("ts"),
        F.expr(sym).alias("sym"),
    )


def assemble(rows: DataFrame, between: str = "") -> DataFrame:
    """SYMBOLS -> (stream_id, text); for keys whose streams fit a row."""
    ordered = F.array_sort(F.collect_list(F.struct("seq", "sym")))
    return rows.groupBy("stream_id").agg(F.array_join(F.transform(ordered, lambda x: x["sym"]), between).alias("text"))


def texts(df: DataFrame, key: str, text: str) -> DataFrame:
    """One text a row; null keys and texts give no row."""
    return df.where(F.expr(f"{key} is not null and ({text}) is not null")).select(F.expr(f"cast({key} as string)").alias("stream_id"), F.expr(text).alias("text"))


def chunks(rows: DataFrame, size: int) -> DataFrame:
    """(stream_id, text) -> CHUNKS of ``size`` symbols; a chunk's row has no more than its own text."""
    cut = F.expr(f"transform(sequence(0, cast(ceil(length(text) / {size}) as int) - 1), i -> struct(cast(i as bigint) chunk_no, cast(i as bigint) * {size} base_off, substring(text, i * {size} + 1, {size}) text))")
    return rows.where(F.length("text") > 0).select("stream_id", F.explode(cut).alias("c")).select("stream_id", "c.chunk_no", "c.base_off", "c.text")


def symbol_chunks(rows: DataFrame, size: int) -> DataFrame:
    """SYMBOLS of one character each -> CHUNKS; no task and no row has more than ``size`` of a stream's symbols."""
    number = F.floor(F.col("seq") / size).cast("long").alias("chunk_no")
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seq", "sym"))), lambda x: x["sym"]), "")
    cut = rows.groupBy("stream_id", number).agg(text.alias("text"))
    return cut.select("stream_id", "chunk_no", (F.col("chunk_no") * size).alias("base_off"), "text")


def numbered(rows: DataFrame, keys: list[str], order: list[str], name: str = "seq") -> DataFrame:
    """``rows`` with each one's place (from 0) among those of its key, whatever a key's size.

    Rows are dealt out in ranges of (keys, order) and sorted; a place is that in its range and
    the sum of the ranges before it.  Ties of the whole order are equal rows or in any order.
    """
    ordered = rows.repartitionByRange(*keys, *order).sortWithinPartitions(*keys, *order)
    ordered = staged(ordered.select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_place")), "ordered")
    begin = ordered.groupBy("_part", *keys).agg(F.min("_place").alias("_first"), F.count(F.lit(1)).alias("_n"))
    by = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # a row for each range
    begin = begin.withColumn("_before", F.coalesce(F.sum("_n").over(by), F.lit(0)))
    return ordered.join(begin, ["_part", *keys]).withColumn(name, F.col("_place") - F.col("_first") + F.col("_before")).drop("_part", "_place", "_first", "_before", "_n")


def _symbol_rows(df: DataFrame, f: Family) -> tuple[DataFrame, list[str]]:
    """(stream_id, order columns, sym) of a family's table, and the names of its order."""
    order = [f"o{i}" for i in range(len(f.order))]
    rows = df.where(F.expr(f"{f.key} is not null and ({f.sym}) is not null"))
    columns = [F.expr(x).alias(o) for x, o in zip(f.order, order, strict=True)]
    return rows.select(F.expr(f"cast({f.key} as string)").alias("stream_id"), *columns, F.expr(f.sym).alias("sym")), [*order, "sym"]


def family_symbols(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(stream_id, seq, sym) of a family of symbols; streams of any length."""
    rows, order = _symbol_rows(load(spark, sf_dir, FAMILIES[name].table), FAMILIES[name])
    return numbered(rows, ["stream_id"], order).select("stream_id", "seq", "sym")


def family_window(spark: SparkSession, sf_dir: str, name: str, capacity: int) -> DataFrame:
    """WINDOWS of a family: the last ``capacity`` symbols are chosen before anything is gathered.

    Every task keeps the last rows of each stream it has before the shuffle, so a stream's history
    never meets in one place; its length is a sum beside it.
    """
    f = FAMILIES[name]
    if f.text or capacity >= WHOLE:
        return window_at(family(spark, sf_dir, name), capacity)
    key = "spark.sql.optimizer.windowGroupLimitThreshold"  # windows of more rows would be cut after the shuffle
    if int(spark.conf.get(key)) < capacity:
        spark.conf.set(key, str(capacity))
    rows, order = _symbol_rows(load(spark, sf_dir, f.table), f)
    seen = rows.groupBy("stream_id").agg((F.sum(F.length("sym")) + (F.count(F.lit(1)) - 1) * len(f.between)).alias("n_seen"))
    by = Window.partitionBy("stream_id").orderBy(*map(F.desc, order))
    if f.between:  # texts: as many of the last as reach the capacity; what stands between two may be the window's first symbol
        reach = F.sum(F.length("sym") + len(f.between)).over(by.rowsBetween(Window.unboundedPreceding, -1)) - len(f.between)
        rows = rows.withColumn("reach", F.coalesce(reach, F.lit(0))).withColumn("back", F.row_number().over(by)).where(F.col("reach") < capacity)
    else:
        rows = rows.withColumn("back", F.row_number().over(by)).where(F.col("back") <= capacity)
    last = F.array_sort(F.collect_list(F.struct((-F.col("back")).alias("at"), "sym")))
    text = F.expr(f"right(whole, {capacity})")
    rows = rows.groupBy("stream_id").agg(F.array_join(F.transform(last, lambda x: x["sym"]), f.between).alias("whole")).select("stream_id", text.alias("win_text"))
    return rows.join(seen, "stream_id").select("stream_id", "n_seen", (F.col("n_seen") - F.length("win_text")).alias("win_start"), "win_text")


def family(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(stream_id, text) of a named stream family, each stream whole in a row."""
    f = FAMILIES[name]
    df = load(spark, sf_dir, f.table)
    if f.text:
        return texts(df, f.key, f.text)
    rows, order = _symbol_rows(df, f)
    ordered = F.array_sort(F.collect_list(F.struct(*order)))
    text: Column = F.array_join(F.transform(ordered, lambda x: x["sym"]), f.between)
    return rows.groupBy("stream_id").agg(text.alias("text"))


def encode_symbols(rows: DataFrame, known: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """SYMBOLS -> (the same with an integer ``code``, dictionary (sym, code)).

    Codes of a ``known`` dictionary stay; symbols that it lacks get the next ones, in order.
    """
    new = rows.select("sym").distinct()
    if known is not None:
        new = new.join(known, "sym", "left_anti")
        first = known.agg(F.coalesce(F.max("code") + 1, F.lit(0)).alias("first"))
    else:
        first = rows.sparkSession.range(1).select(F.lit(0).cast("long").alias("first"))
    codes = numbered(new.select("sym", F.lit(0).alias("all")), ["all"], ["sym"], "place")
    codes = codes.join(F.broadcast(first)).select("sym", (F.col("first") + F.col("place")).alias("code"))  # one row
    codes = staged(codes if known is None else known.select("sym", F.col("code").cast("long").alias("code")).unionByName(codes), "codes")
    return rows.join(codes, "sym"), codes
