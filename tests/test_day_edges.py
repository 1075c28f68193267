"""Moments at the edges of days, beside the SQL twins."""

import pytest

from phasewarp.plans import catalogue

TIMES = ["2023-12-31 12:00:00", "2023-12-31 23:59:59.7", "2024-01-01 00:00:00", "2024-01-01 23:59:59.4", "2024-01-01 23:59:59.5", "2024-01-02 23:59:58.5",
         "2024-01-02 23:59:59.500001", "2024-01-03 23:59:59.499999", "2024-01-30 23:59:59.9", "2024-02-01 08:00:00"]


@pytest.mark.parametrize("name", ["phase_day", "sql_recursive_days"])
def test_days_equal_sql(spark, tmp_path, name):
    duckdb = pytest.importorskip("duckdb")
    rows = spark.createDataFrame(list(enumerate(TIMES)), "event_id long, ts string").selectExpr("event_id", "CAST(ts AS TIMESTAMP) AS ts")
    rows.write.parquet(str(tmp_path / "events.parquet"))
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    assert sorted(map(tuple, catalogue.QUERIES[name](spark, str(tmp_path)).collect())) == sorted(con.execute(catalogue.SQL[name]).fetchall())
