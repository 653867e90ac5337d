"""Every registered query beside its SQL, on the smallest tables."""

import datetime
import math
from decimal import Decimal
from pathlib import Path

import duckdb
import pytest

from winsub import relational_workloads, workloads

ORACLES = workloads.ORACLES | relational_workloads.ORACLES
QUERIES = workloads.QUERIES | relational_workloads.QUERIES


@pytest.fixture(scope="module")
def db(sf_dir):
    c = duckdb.connect()
    for p in Path(sf_dir).glob("*.parquet"):
        c.sql(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}{'/*.parquet' if p.is_dir() else ''}'")
    return c


def plain(v):
    if isinstance(v, Decimal):
        v = float(v)
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6)
    return v.isoformat() if isinstance(v, datetime.datetime) else v


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_is_its_sql(spark, sf_dir, db, name):
    found, want = QUERIES[name](spark, sf_dir), db.sql(ORACLES[name])
    columns = sorted(found.columns)
    assert columns == sorted(want.columns)
    a = sorted((tuple(plain(r[c]) for c in columns) for r in found.collect()), key=repr)
    at = [want.columns.index(c) for c in columns]
    b = sorted((tuple(plain(r[i]) for i in at) for r in want.fetchall()), key=repr)
    assert a == b


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_query_gives_rows(spark, sf_dir, name):
    assert QUERIES[name](spark, sf_dir).count() > 0


def test_range_join_of_a_long_stream(spark, tmp_path):
    """Hits beyond the first 200 segments."""
    kind = "if(id in (7, 8, 9) or id > 209996, 'click', 'error')"
    rows = spark.range(210_000).selectExpr("id event_id", "cast(0 as long) user_id", "timestamp_micros(id) ts", f"{kind} event_type")
    rows.write.parquet(f"{tmp_path}/events.parquet")
    found = QUERIES["rel_range_join"](spark, str(tmp_path))
    assert sorted(map(tuple, found.collect())) == [(0, 7), (205, 209_997)]


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_window_that_begins_with_what_stands_between_texts(spark, tmp_path):
    """The last text fills the window but for one symbol, which is the line feed before it."""
    rows = [(1, 0, "u", "the"), (1, 1, "a", "x" * 2047), (2, 0, "u", "the"), (2, 1, "a", "x" * 2048), (3, 0, "u", "the"), (3, 1, "a", "x" * 2046)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    found = QUERIES["locate_conv"](spark, str(tmp_path))
    assert sorted(map(tuple, found.collect())) == [(1, "\n", 2051, 3), (3, "\n", 2050, 3)]


def test_broadcast_query_sees_all_of_its_time(spark, tmp_path):
    """Events of one time in several files; a query meets every event of its time, whatever the file and number."""
    rows = [(500, 1, 5, "view"), (1500, 2, 5, "error"), (1501, 2, 5, "view"), (1502, 2, 6, "error"), (1503, 2, 7, "view"), (3, 3, 9, "error"), (1000, 1, 8, "view")]
    for e, u, t, kind in rows:
        spark.range(1).selectExpr(f"cast({e} as long) event_id", f"cast({u} as long) user_id", f"timestamp_micros({t}) ts", f"'{kind}' event_type").write.mode("append").parquet(f"{tmp_path}/events.parquet")
    found = QUERIES["stream_locate_broadcast"](spark, str(tmp_path))
    # Two queries at 5 see "ev", the one at 8 sees "evev".
    assert sorted(map(tuple, found.collect())) == [(2, "ev", 2, 0), (2, "ev", 2, 0), (2, "ev", 4, 0), (2, "ev", 4, 2)]
