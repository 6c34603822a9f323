"""Queries against their DuckDB text on the smallest tables."""

import glob
import os

import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
NAMES = [n for n in entry.oracle_sql() if not n.startswith("op")]


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, duck, name):
    got = entry.queries()[name](spark, SF)
    want = duck.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(got.columns)
    rows = sorted(tuple(str(r[c]) for c in columns) for r in got.collect())
    assert rows == sorted(tuple(str(x) for x in r) for r in want.fetchall())


def same_as_sql(spark, folder, name):
    """The rows of a query over a folder of its own, after they are held against its SQL."""
    import duckdb

    con = duckdb.connect()
    for path in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    want = con.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    rows = sorted(tuple(str(r[c]) for c in columns) for r in entry.queries()[name](spark, str(folder)).collect())
    assert rows == sorted(tuple(str(x) for x in r) for r in want.fetchall())
    return rows


def events_at(folder, *times):
    """An events table of the given times, all of one type."""
    import duckdb

    rows = ", ".join(f"({i}::BIGINT, {t and repr(t)}::TIMESTAMP, 1::BIGINT, 'view', {i + 1}.5::DOUBLE, '{{}}')".replace("None", "NULL") for i, t in enumerate(times))
    duckdb.sql(f"COPY (SELECT * FROM (VALUES {rows}) t(event_id, ts, user_id, event_type, value, props)) TO '{folder}/events.parquet' (FORMAT parquet)")


def test_days_of_times_near_their_ends(spark, tmp_path):
    """Half a second or less before midnight is the next day in the SQL (a half goes to the even second); null and early times have groups."""
    events_at(tmp_path, "2024-01-02 23:59:59.7", "2024-01-02 23:59:59.5", "2024-01-02 23:59:58.5", "2024-01-02 23:59:59.499999", "2024-01-03 00:00:00.2", None, "1969-12-31 12:00:00", "1968-12-31 12:00:00")
    rows = same_as_sql(spark, tmp_path, "rel_time_windows")
    assert ("view", "1704240000", "3") in rows and ("view", "None", "1") in rows and len(rows) == 5


def test_windows_of_times_near_their_ends(spark, tmp_path):
    """As of days; a window is given out when the watermark is just at its end."""
    events_at(tmp_path, "2024-01-06 01:00:00", "2024-01-07 23:59:59.7", "2024-01-07 23:59:59.5", "2024-01-08 00:00:01", "2024-01-18 00:59:59.6")
    rows = same_as_sql(spark, tmp_path, "stream_windowed_sketch")
    assert len(rows) == 4 and len({r[0] for r in rows}) == 2


def test_entry(spark):
    assert entry.entry(spark).count() == 5
