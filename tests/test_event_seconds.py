"""Fractions of a second in the rolling count, against DuckDB."""

import datetime as dt

import duckdb

import __spark_entry__ as entry


def test_seconds_are_rounded_as_in_sql(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    offsets = [0.0, 0.4, 0.5, 1.5, 2.5, 86399.6, 86400.4, 86400.5, 86400.6, 86401.5, 86402.5, -1.5e9 - 0.5, -1.5e9 + 86399.7, -1.5e9 + 86400.5]
    rows = [(i, start + dt.timedelta(seconds=s), i % 2 if i < 3 else 0) for i, s in enumerate(offsets)]
    path = str(tmp_path / "events.parquet")
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long").write.parquet(path)
    got = {tuple(r) for r in entry.queries()["q_rolling_events"](spark, str(tmp_path)).collect()}
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{path}/*.parquet')")
    assert got == set(con.execute(entry.oracle_sql()["q_rolling_events"]).fetchall())
