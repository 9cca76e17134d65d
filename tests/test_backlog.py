"""`backlog_stream` against its SQL at the ends of hours, where the session's time zone is not UTC, and with events that have no user."""

import duckdb
import pytest

from tests.conftest import check_query, rows_of
from tilestar import registry

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()
NAME = "backlog_stream"


@pytest.fixture(params=["UTC", "America/New_York", "Asia/Kolkata"])
def zone(spark, request):
    before = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", request.param)
    yield
    spark.conf.set("spark.sql.session.timeZone", before)


def test_hours_in_any_zone(spark, duck, zone):
    check_query(spark, duck, QUERIES, ORACLES, NAME)


def check_events(spark, path, rows):
    """rows: SQL of ts and user_id."""
    con, file = duckdb.connect(), f"{path}/events.parquet"
    con.sql(f"COPY (SELECT row_number() OVER () AS event_id, ts, user_id, 'view' AS event_type, 1.0::DOUBLE AS value, '{{}}' AS props FROM ({rows})) TO '{file}' (FORMAT parquet)")
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{file}'")
    assert rows_of(QUERIES[NAME](spark, str(path)).toPandas()) == rows_of(con.sql(ORACLES[NAME]).df())


def test_ends_of_hours(spark, tmp_path):
    """SQL rounds to milliseconds: the last 500 microseconds of an hour count in the next one."""
    check_events(spark, tmp_path, "SELECT TIMESTAMP '2024-01-01 00:00:00' + to_hours(h::INT) + to_microseconds(us) AS ts, h + us AS user_id FROM range(1, 13) t(h), unnest([-501, -500, -499, -1, 0, 1, 499, 500]) u(us)")


def test_clock_changes_and_no_user(spark, zone, tmp_path):
    """Clocks in New York skip 2 o'clock on 10 March 2024 and have 1 o'clock twice on 3 November 2024."""
    some = "SELECT TIMESTAMP '{} 23:50:00' + to_minutes(n::INT * 20) AS ts, n FROM range(40) t(n)"
    check_events(spark, tmp_path, f"SELECT ts, CASE WHEN n % 9 > 0 THEN n END AS user_id FROM ({some.format('2024-03-09')} UNION ALL {some.format('2024-11-02')})")
