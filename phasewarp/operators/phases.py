"""Event spans cut into phases."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Seconds of the resolutions of fixed length.
STEP = {"minute": 60, "half hour": 1800, "hour": 3600, "day": 86400, "week": 604800}


def phase_of(ts: Column, resolution: str = "day", origin: str = "2024-01-01 00:00:00") -> Column:
    """1-based number of the phase that holds ``ts``."""
    if resolution == "month":
        start = F.to_timestamp(F.lit(origin))
        return ((F.year(ts) - F.year(start)) * 12 + F.month(ts) - F.month(start) + 1).cast("int")
    return (F.floor((F.unix_timestamp(ts) - F.unix_timestamp(F.lit(origin))) / STEP[resolution]) + 1).cast("int")


def epoch_of(ts: Column) -> Column:
    """Seconds of ``ts``, with or without time zone, since 1970, with their fraction, as SQL's ``epoch``:
    a time without zone counts as UTC, whatever the session's zone."""
    micros = F.pmod(F.unix_micros(ts.cast("timestamp")), F.lit(1_000_000))
    # whole seconds only: of those with a fraction, unix_timestamp goes towards 1970
    return (F.unix_timestamp(F.timestamp_add("MICROSECOND", -micros, ts)) * 1_000_000 + micros) / F.lit(1e6)


def nearest_phase_of(ts: Column, resolution: str = "day", origin: str = "2024-01-01 00:00:00") -> Column:
    """The same of the nearest whole second, ties to the even one; less than a phase before the
    origin, which is in UTC, counts as phase 1."""
    seconds = F.rint(epoch_of(ts) - F.unix_timestamp(F.lit(origin).cast("timestamp_ntz"))).cast("long")
    return (F.call_function("div", seconds, F.lit(STEP[resolution])) + 1).cast("int")


def assign(records: DataFrame, resolution: str = "day", origin: str = "2024-01-01 00:00:00", n: int | None = None) -> DataFrame:
    """Records with ``phase``; with ``n``, those outside the span go."""
    out = records.withColumn("phase", phase_of(F.col("ts"), resolution, origin))
    return out.filter(F.col("phase").between(1, n)) if n else out


def densify(series: DataFrame, n: int | None = None, value: str = "pop") -> DataFrame:
    """Every phase from 1 to ``n`` (default: the event's last) of every event and medium; phases
    without records are data points with value 0."""
    per = series.groupBy("event", "medium").agg(F.max("phase").alias("_last"))
    last = F.lit(n) if n else F.max("_last").over(Window.partitionBy("event"))
    grid = per.withColumn("_n", last).select("event", "medium", F.explode(F.sequence(F.lit(1), F.col("_n").cast("int"))).alias("phase"))
    return grid.join(series, ["event", "medium", "phase"], "left").withColumn(value, F.coalesce(F.col(value), F.lit(0.0)))


def start_of(phase: Column, resolution: str = "day", origin: str = "2024-01-01 00:00:00") -> Column:
    if resolution == "month":
        return F.add_months(F.to_timestamp(F.lit(origin)), phase - 1).cast("timestamp")
    return F.timestamp_seconds(F.unix_timestamp(F.lit(origin)) + (phase - 1) * STEP[resolution])
