"""Every query beside its SQL twin: ``python tests/twins.py SF_DIR [NAME...]`` prints one line a query."""

from __future__ import annotations

import datetime
import decimal
import math
import os
import sys
import time

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v, digits: int | None = None):
    """A value as both engines would print it; with ``digits`` floats to so many significant ones."""
    if isinstance(v, (list, tuple)):
        return tuple(plain(x, digits) for x in v)
    if isinstance(v, dict):
        return tuple((k, plain(x, digits)) for k, x in sorted(v.items()))
    if isinstance(v, decimal.Decimal):
        v = float(v) if v % 1 else int(v)
    if isinstance(v, float):
        if math.isnan(v):
            return "nan"
        return float(f"{v:.{digits}g}") + 0.0 if digits else v + 0.0
    if isinstance(v, (datetime.datetime, datetime.date)):
        return v.isoformat()
    if isinstance(v, bytearray):
        return bytes(v)
    return v


def rows_of(names: list[str], rows, digits: int | None = None) -> list[str]:
    order = sorted(range(len(names)), key=lambda k: names[k])
    return sorted(repr(tuple(plain(r[k], digits) for k in order)) for r in rows)


def views(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def differ(spark, con, make, sql: str, sf_dir: str) -> str:
    """Empty where both give the same rows, else what differs."""
    df = make(spark, sf_dir)
    got = [r.asDict(recursive=True) for r in df.collect()]
    names = df.columns
    got = [tuple(r[n] for n in names) for r in got]
    cur = con.execute(sql)
    told, want = [c[0] for c in cur.description], cur.fetchall()
    if sorted(names) != sorted(told):
        return f"columns {sorted(names)} and {sorted(told)}"
    if len(got) != len(want):
        return f"{len(got)} rows and {len(want)}"
    if rows_of(names, got) == rows_of(told, want):
        return ""
    a, b = rows_of(names, got, 9), rows_of(told, want, 9)
    if a == b:
        return "equal to nine digits only"
    apart = [(x, y) for x, y in zip(a, b) if x != y]
    return f"{len(apart)} of {len(a)} rows differ, as {apart[0][0][:200]} and {apart[0][1][:200]}"


def main(sf_dir: str, names: list[str]) -> None:
    sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])
    spark = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.driver.memory", "10g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", "file:///tmp/twins-shared")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    con, made, sqls = views(sf_dir), entry.queries(), entry.oracle_sql()
    for name in names or sqls:
        began = time.time()
        try:
            said = differ(spark, con, made[name], sqls[name], sf_dir) or "same"
        except Exception as e:  # noqa: BLE001  (the next queries are still wanted)
            said = f"error {type(e).__name__} {str(e)[:300]!r}"
        print(f"{time.time() - began:6.1f}  {name}: {said}", flush=True)


if __name__ == "__main__":
    main(sys.argv[1], sys.argv[2:])
