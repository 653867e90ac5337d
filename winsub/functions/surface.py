"""SQL functions: scalar, aggregate and table functions over texts and windows."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult
from pyspark.sql.types import ArrayType, LongType, StringType, StructField, StructType

from winsub.kernel.scan import native_find
from winsub.kernel.window_index import WindowIndex

TAIL = StructType([StructField(x, StringType() if x == "kind" else LongType()) for x in ("start", "len", "kind", "twin", "period")])


@F.pandas_udf(ArrayType(LongType()))
def substr_positions(text: pd.Series, pattern: pd.Series) -> pd.Series:
    """All places of a pattern; null for a null text or pattern."""

    def one(t: str | None, p: str | None) -> list[int] | None:
        if t is None or p is None:
            return None
        if not p:
            raise ValueError("an empty pattern")
        return native_find(t, p)[0]

    return pd.Series([one(t, p) for t, p in zip(text, pattern, strict=True)])


def _tail(text: str | None) -> dict | None:
    if text is None:
        return None
    x = WindowIndex(max(1, len(text))).extend(text)
    twin, period = x.tail_period() or (None, None)
    return {"start": x.tail_start, "len": x.tail_len, "kind": x.cursor_kind(), "twin": twin, "period": period}


@F.pandas_udf(TAIL)
def window_tail(text: pd.Series) -> pd.DataFrame:
    """The repeated tail of a window."""
    rows = [_tail(t) or dict.fromkeys(("start", "len", "kind", "twin", "period")) for t in text]
    return pd.DataFrame(rows, columns=["start", "len", "kind", "twin", "period"]).astype({"start": "Int64", "len": "Int64", "twin": "Int64", "period": "Int64"})


@F.pandas_udf(LongType())
def tail_agg(seq: pd.Series, sym: pd.Series) -> int:
    """Tail length of a group's symbols in the order of ``seq``."""
    return WindowIndex(max(1, len(sym))).extend(sym.iloc[seq.argsort(kind="stable")]).tail_len


class LocateIn:
    """``locate_in(text, pattern)``: one row for every match."""

    def eval(self, text: str, pattern: str) -> Iterator[tuple[int]]:
        if text is not None and pattern is not None:
            for i in native_find(text, pattern)[0]:
                yield (i,)


class LocateInTable:
    """``locate_in_table(TABLE(t) PARTITION BY key ORDER BY (...), patterns, capacity)``.

    The table's last column is the symbol; patterns are joined by a vertical bar.
    """

    @staticmethod
    def analyze(rows: AnalyzeArgument, patterns: AnalyzeArgument, capacity: AnalyzeArgument) -> AnalyzeResult:
        fields = [StructField("key", StringType()), StructField("pattern", StringType()), StructField("n_seen", LongType()), StructField("off", LongType())]
        return AnalyzeResult(StructType(fields))

    def __init__(self, *args):
        self.index, self.patterns, self.key = None, "", None

    def eval(self, row, patterns: str, capacity: int) -> None:
        if self.index is None:
            self.index, self.patterns, self.key = WindowIndex(capacity), patterns, str(row[0])
        self.index.push(row[len(row) - 1])

    def terminate(self) -> Iterator[tuple[str, str, int, int]]:
        if self.index is not None:
            for p in self.patterns.split("|"):
                for off in self.index.locate(p):
                    yield self.key, p, self.index.n_seen, off


TAIL_SQL = """
CREATE OR REPLACE TEMPORARY FUNCTION repeated_tail(t STRING) RETURNS INT RETURN
  aggregate(sequence(1, 32), named_struct('lo', 0, 'hi', greatest(length(t) - 1, 0)),
    (a, i) -> if(a.lo >= a.hi, a,
      if(instr(left(t, length(t) - 1), right(t, cast(floor((a.lo + a.hi + 1) / 2) as int))) > 0,
        named_struct('lo', cast(floor((a.lo + a.hi + 1) / 2) as int), 'hi', a.hi),
        named_struct('lo', a.lo, 'hi', cast(floor((a.lo + a.hi + 1) / 2) as int) - 1))),
    a -> a.lo)
"""


def register_all(spark: SparkSession) -> None:
    """Install every function of this module in the session."""
    spark.udf.register("substr_positions", substr_positions)
    spark.udf.register("window_tail", window_tail)
    spark.udf.register("tail_agg", tail_agg)
    spark.udtf.register("locate_in", F.udtf(LocateIn, returnType="off bigint"))
    spark.udtf.register("locate_in_table", F.udtf(LocateInTable))
    spark.sql(TAIL_SQL)
