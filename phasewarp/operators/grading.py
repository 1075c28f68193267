"""Relative grades of methods per event."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from phasewarp.operators.alignment import METHODS


def path_fingerprint(matches: DataFrame) -> DataFrame:
    steps = F.concat_ws(",", F.transform(F.array_sort(F.collect_list(F.struct("k", "i", "j"))), lambda s: F.concat_ws(":", s["i"].cast("string"), s["j"].cast("string"))))
    return matches.groupBy("event", "method").agg(F.md5(steps).alias("path_md5"))


def rank_methods(matches: DataFrame, defects: DataFrame) -> DataFrame:
    """Methods without defects come first, then fewer defects; equal alignments are told apart by
    complexity, the simpler one first."""
    order = F.lit(99)
    for m in METHODS.values():
        order = F.when(F.col("method") == m.name, m.order).otherwise(order)
    joined = defects.join(path_fingerprint(matches), ["event", "method"]).withColumn("n_defects", F.col("n_singular") + F.col("n_far"))
    joined = joined.withColumn("complexity", order.cast("int"))
    same = Window.partitionBy("event", "path_md5").orderBy("complexity")
    tied = joined.withColumn("behind", (F.dense_rank().over(same) - 1).cast("int"))
    best = Window.partitionBy("event").orderBy((F.col("n_defects") > 0).cast("int"), "n_defects", "behind")
    return tied.withColumn("grade", F.dense_rank().over(best)).select("event", "method", "n_singular", "n_far", "path_md5", "complexity", "grade")


def totals(grades: DataFrame) -> DataFrame:
    return grades.groupBy("method").agg(F.sum("grade").alias("grade_sum"), F.sum((F.col("n_singular") + F.col("n_far") > 0).cast("int")).alias("n_defective"), F.min("grade").alias("best"), F.max("grade").alias("worst"))
