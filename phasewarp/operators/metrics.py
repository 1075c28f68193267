"""Measures of an alignment."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phasewarp.operators import distances


def require_same_span(series: DataFrame) -> DataFrame:
    """The series, or an error where an event's media have different numbers of phases."""
    n = series.groupBy("event", "medium").agg(F.count("*").alias("n")).groupBy("event").agg(F.count_distinct("n").alias("k"))
    fine = F.when(F.col("k") == 1, F.lit(True)).otherwise(F.raise_error(F.concat(F.lit("unequal spans of event "), "event")).cast("boolean"))
    return series.join(F.broadcast(n.withColumn("ok", fine)), "event").filter("ok").drop("k", "ok")


def attach(matches: DataFrame, series: DataFrame) -> DataFrame:
    s = distances.slopes(series)
    side = lambda medium, n, v, w: s.filter(F.col("medium") == medium).select("event", F.col("phase").alias(n), F.col("pop_norm").alias(v), F.col("slope").alias(w))
    return matches.join(side("A", "i", "a", "sa"), ["event", "i"]).join(side("B", "j", "b", "sb"), ["event", "j"])


def summary(matches: DataFrame, series: DataFrame) -> DataFrame:
    """Shape and altitude similarity (1 - mean slope or level distance over matches) and leads.

    ``delta_a_printed`` sums i - j over matches with i > j, per phase of A; since A then shows
    the feature later, ``lead_a`` sums j - i over j > i, and the other two swap the media.
    """
    sizes = series.groupBy("event").agg(F.sum((F.col("medium") == "A").cast("double")).alias("n"), F.sum((F.col("medium") == "B").cast("double")).alias("m"))
    later = lambda x, y: F.sum(F.when(F.col(x) > F.col(y), F.col(x) - F.col(y)).otherwise(0)).cast("double")
    out = attach(matches, series).groupBy("event", "method").agg(
        (1 - F.avg(F.abs(F.col("sa") - F.col("sb")))).alias("psi_s"),
        (1 - F.avg(F.abs(F.col("a") - F.col("b")))).alias("psi_a"),
        later("i", "j").alias("_ij"), later("j", "i").alias("_ji"), F.count("*").alias("n_matches"),
    )
    return out.join(F.broadcast(sizes), "event").select(
        "event", "method", "psi_s", "psi_a",
        (F.col("_ij") / F.col("n")).alias("delta_a_printed"), (F.col("_ji") / F.col("m")).alias("delta_b_printed"),
        (F.col("_ji") / F.col("n")).alias("lead_a"), (F.col("_ij") / F.col("m")).alias("lead_b"), "n_matches",
    )


def path_stats(aligned: DataFrame) -> DataFrame:
    last = F.element_at(F.element_at("g", -1), -1)
    return aligned.select("event", "method", F.size("path").alias("n_matches"), last.alias("cost"))
