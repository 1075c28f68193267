"""Distances between phases of two series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def slopes(series: DataFrame, value: str = "pop_norm") -> DataFrame:
    """Estimated derivative: the mean of the backward step and half the centred two-step
    difference; end points copy their inner neighbour, series under three points have 0."""
    by = Window.partitionBy("event", "medium").orderBy("phase")
    last, following = F.lag(value).over(by), F.lead(value).over(by)
    inner = series.withColumn("slope", (F.col(value) - last + (following - last) / 2) / 2)
    return inner.withColumn("slope", F.coalesce("slope", F.lead("slope").over(by), F.lag("slope").over(by), F.lit(0.0)))


def level(a: Column, b: Column) -> Column:
    return F.abs(a - b)


slope_distance = level


def compound(vocab: Column, level_part: Column, slope_part: Column) -> Column:
    """Square root of the product of the three distances."""
    return F.sqrt(F.greatest(vocab * level_part * slope_part, F.lit(0.0)))


def temporal_weight(i: Column, j: Column, eta: float = 10.0, tau: float = 2.0) -> Column:
    """Sigmoid penalty of the offset, one half at ``tau`` (in phases)."""
    return 1 / (1 + F.exp(F.least(F.lit(700.0), -F.lit(float(eta)) * (F.abs(i - j).cast("double") - F.lit(float(tau))))))


def total(compound_part: Column, omega: Column) -> Column:
    return compound_part + omega


def cell_grid(series: DataFrame, value: str = "pop_norm") -> DataFrame:
    """``event, i, j, a, b, sa, sb``: every phase of A against every phase of B, by an equi-join
    on the event."""
    s = slopes(series, value)
    a = s.filter("medium = 'A'").select("event", F.col("phase").alias("i"), F.col(value).alias("a"), F.col("slope").alias("sa"))
    b = s.filter("medium = 'B'").select("event", F.col("phase").alias("j"), F.col(value).alias("b"), F.col("slope").alias("sb"))
    return a.join(b, "event")
