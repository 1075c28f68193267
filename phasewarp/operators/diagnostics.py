"""Defects of alignments, peaks of series, bursts and robustness."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SERIES = ["event", "medium"]


def singular_points(matches: DataFrame, limit: int = 4) -> DataFrame:
    """Points matched to more than ``limit`` points of the other series."""
    side = lambda own, medium: matches.groupBy("event", "method", F.col(own).alias("point")).agg(F.count("*").alias("n_matched")).filter(F.col("n_matched") > limit).withColumn("medium", F.lit(medium))
    return side("i", "A").unionByName(side("j", "B"))


def far_matches(matches: DataFrame, limit: int = 2) -> DataFrame:
    return matches.withColumn("offset", F.abs(F.col("i") - F.col("j"))).filter(F.col("offset") > limit)


def defects(matches: DataFrame, singular_limit: int = 4, far_limit: int = 2) -> DataFrame:
    """``event, method, n_singular, n_far``, zeros included."""
    base = matches.select("event", "method").distinct()
    s = singular_points(matches, singular_limit).groupBy("event", "method").agg(F.count("*").alias("n_singular"))
    f = far_matches(matches, far_limit).groupBy("event", "method").agg(F.count("*").alias("n_far"))
    return base.join(s, ["event", "method"], "left").join(f, ["event", "method"], "left").fillna(0, ["n_singular", "n_far"])


def peaks(series: DataFrame, value: str = "pop_norm", least: float = 0.0) -> DataFrame:
    """Phases above both neighbours (the first of equals) by more than ``least``."""
    by = Window.partitionBy(*SERIES).orderBy("phase")
    last, following = F.coalesce(F.lag(value).over(by), F.lit(-1.0)), F.coalesce(F.lead(value).over(by), F.lit(-1.0))
    return series.withColumn("_l", last).withColumn("_f", following).filter((F.col(value) > F.col("_l")) & (F.col(value) >= F.col("_f")) & (F.col(value) - F.least("_l", "_f") > least)).drop("_l", "_f")


def top_peaks(series: DataFrame, k: int, value: str = "pop_norm") -> DataFrame:
    by = Window.partitionBy(*SERIES).orderBy(F.desc(value), "phase")
    return peaks(series, value).withColumn("peak_rank", F.row_number().over(by)).filter(F.col("peak_rank") <= k)


def peak_recall(found: DataFrame, calendar: DataFrame, tolerance: int = 0) -> DataFrame:
    """Share of dated sub-events ``event, medium, day`` that have a peak within the tolerance."""
    near = calendar.join(found.select(*SERIES, "phase"), SERIES, "left").groupBy(*SERIES, "day").agg(F.coalesce(F.max((F.abs(F.col("phase") - F.col("day")) <= tolerance).cast("int")), F.lit(0)).alias("hit"))
    return near.groupBy(*SERIES).agg(F.count("*").alias("n_events"), F.sum("hit").alias("n_hit"), (F.sum("hit") / F.count("*")).alias("recall"))


def burst_gain(series: DataFrame, value: str = "pop_norm") -> DataFrame:
    """Value and rise over the phase before."""
    by = Window.partitionBy(*[c for c in ("event", "medium", "method") if c in series.columns]).orderBy("phase")
    return series.withColumn("rise", F.col(value) - F.coalesce(F.lag(value).over(by), F.lit(0.0)))


def burst_alert(series: DataFrame, window: int = 3, factor: float = 2.0, value: str = "pop_norm") -> DataFrame:
    """Phases whose value exceeds ``factor`` times the mean of the ``window`` phases before."""
    by = Window.partitionBy(*SERIES).orderBy("phase").rowsBetween(-window, -1)
    return series.withColumn("trailing", F.avg(value).over(by)).filter(F.col(value) > F.lit(float(factor)) * F.col("trailing"))


def flatness(series: DataFrame, value: str = "pop_norm") -> DataFrame:
    """Largest deviation from the horizontal line, and the coefficient of variation."""
    keys = [c for c in ("event", "medium", "method") if c in series.columns]
    n = F.count("*").over(Window.partitionBy(*keys))
    return series.withColumn("_d", F.abs(F.col(value) - 1 / n)).groupBy(*keys).agg(F.max("_d").alias("max_dev"), (F.stddev_pop(value) / F.avg(value)).alias("cv"))


def peak_class(series: DataFrame, value: str = "pop_norm", prominent: float = 2.0, alike: float = 0.4) -> DataFrame:
    """``single``: one prominent peak; ``multiple``: several of similar height; ``hybrid``: one
    that dominates several small ones.  Prominent: over ``prominent`` times the series' mean; the
    peaks of a run of neighbouring phases count once because lower shoulders are no peaks."""
    mean = F.avg(value).over(Window.partitionBy(*SERIES))
    strong = peaks(series.withColumn("_m", mean), value).filter(F.col(value) > F.lit(prominent) * F.col("_m") * 0.5)
    top = F.max(value).over(Window.partitionBy(*SERIES))
    counted = strong.withColumn("_t", top).groupBy(*SERIES).agg(F.count("*").alias("n_peaks"), F.sum((F.col(value) >= F.lit(alike) * F.col("_t")).cast("int")).alias("n_high"))
    return counted.withColumn("peak_class", F.when(F.col("n_peaks") == 1, "single").when(F.col("n_high") > 1, "multiple").otherwise("hybrid"))


def peak_gaps(found: DataFrame) -> DataFrame:
    by = Window.partitionBy(*SERIES).orderBy("phase")
    gaps = found.withColumn("gap", F.col("phase") - F.lag("phase").over(by)).filter("gap IS NOT NULL")
    return gaps.groupBy(*SERIES).agg(F.count("*").alias("n_gaps"), F.avg("gap").alias("mean_gap"), F.min("gap").alias("least_gap"), F.max("gap").alias("most_gap"))
