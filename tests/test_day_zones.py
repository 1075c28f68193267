"""Events with and without a time zone, beside the SQL twins, in sessions of several zones."""

import pytest

from phasewarp.plans import catalogue

TIMES = ["1969-12-30 23:59:59.7", "1969-12-31 23:59:59.5", "2023-12-31 23:59:59.4", "2024-01-01 00:00:00", "2024-01-01 23:59:59.5", "2024-01-02 04:30:00", "2024-01-02 23:59:58.5",
         "2024-01-03 23:59:59.499999", "2024-01-29 23:59:59.500001", "2024-03-10 02:30:00.25", "2024-07-01 23:30:00", None]


@pytest.mark.parametrize("zone", ["UTC", "America/New_York", "Asia/Kolkata"])
@pytest.mark.parametrize("kind", ["TIMESTAMP_NTZ", "TIMESTAMP"])
@pytest.mark.parametrize("name", ["phase_day", "sql_recursive_days"])
def test_days_equal_sql_in_any_zone(spark, tmp_path, name, kind, zone):
    duckdb = pytest.importorskip("duckdb")
    rows = spark.createDataFrame(list(enumerate(TIMES)), "event_id long, ts string").selectExpr("event_id", f"CAST(ts AS {kind}) AS ts")
    rows.write.parquet(str(tmp_path / "events.parquet"))
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    expected = con.execute(catalogue.SQL[name]).fetchall()
    before = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", zone)
    try:
        got = list(map(tuple, catalogue.QUERIES[name](spark, str(tmp_path)).collect()))
    finally:
        spark.conf.set("spark.sql.session.timeZone", before)
    assert sorted(got, key=str) == sorted(expected, key=str)


def test_events_are_counted_before_the_join(spark, sf):
    plan = catalogue.QUERIES["sql_recursive_days"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    below = plan[plan.index("Join LeftOuter"):]
    assert "Aggregate" in below[:below.index(" Relation [")]
