"""Queries on events whose seconds have fractions, against their SQL."""

from datetime import datetime, timedelta

import pytest

from curvetide import catalogue

duckdb = pytest.importorskip("duckdb")
START = datetime(2024, 1, 1)


def _at(second):
    return START + timedelta(microseconds=round(second * 1e6))


#: The span's ends are met or missed by the second's rounding; 1.5 and 2.5 both are second 2.
#: One event has no user, one no time, and one id occurs twice.
ROWS = [(1, _at(0.6), 7, 1.0), (2, _at(1.5), 7, 2.0), (3, _at(2.5), 7, 4.0), (4, _at(86400.4), 7, 8.0), (5, _at(86401.4), 7, 16.0), (6, _at(86402.6), 7, 32.0), (7, _at(604801.4), 7, 64.0), (8, _at(604800.5), 7, 128.0), (9, _at(5), None, 1.0), (10, None, 7, 1.0), (11, _at(9), 8, 1.0), (11, _at(19), 8, None)]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("sf"))
    spark.createDataFrame(ROWS, "event_id long, ts timestamp_ntz, user_id long, value double").coalesce(1).write.parquet(f"{path}/events.parquet")
    return path


@pytest.mark.parametrize("name", ["events_interval_join", "events_trailing_features"])
def test_fractions_of_seconds(spark, folder, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet/*.parquet'")
    want = con.execute(f"SELECT event_id, n, v FROM ({catalogue.oracle_sql()[name]})").fetchall()
    got = catalogue.queries()[name](spark, folder).select("event_id", "n", "v").collect()
    assert sorted(map(str, want)) == sorted(str(tuple(r)) for r in got)
