"""Phase-vocabulary distance: sign random projections and the exact cosine they stand for."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 63


def gaussian(word: Column, level: Column, seed: int = 42) -> Column:
    """A standard normal number per word and projection, the same on every medium and engine:
    two uniforms from an MD5, then the polar formula."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), word, level.cast("string")))
    number = lambda at: (F.conv(F.substring(digest, at, 8), 16, 10).cast("double") + 1) / F.lit(2.0**32 + 1)
    return F.sqrt(-2 * F.ln(number(1))) * F.cos(2 * math.pi * number(9))


def sign_projection(contributive: DataFrame, s: int = 64, seed: int = 42) -> DataFrame:
    """``event, medium, phase, bits``: s signs packed 63 to a number.  A word's numbers are drawn
    once a series, not once a phase.  Sums combine before the shuffle; no matrix of vocabulary x s
    exists anywhere."""
    keys = ["event", "medium", "phase"]
    at = contributive.groupBy("event", "medium", "word").agg(F.collect_list("phase").alias("_at"))
    levels = at.withColumn("l", F.explode(F.sequence(F.lit(0), F.lit(s - 1)))).withColumn("_z", gaussian(F.col("word"), F.col("l"), seed))
    sums = levels.select("event", "medium", "l", "_z", F.explode("_at").alias("phase")).groupBy(*keys, "l").agg(F.sum("_z").alias("z"))
    words = sums.groupBy(*keys, F.expr(f"l div {BITS}").alias("at")).agg(F.bit_or(F.when(F.col("z") >= 0, F.call_function("shiftleft", F.lit(1).cast("long"), F.col("l") % BITS)).otherwise(F.lit(0).cast("long"))).alias("bits"))
    return words.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "bits"))), lambda x: x["bits"]).alias("bits"))


def empty_signature(s: int) -> Column:
    """All signs +1: what a phase without contributive words gets."""
    full = [(1 << min(BITS, s - k)) - 1 for k in range(0, s, BITS)]
    return F.array(*[F.lit(v).cast("long") for v in full])


def distance(a: Column, b: Column, s: int) -> Column:
    """1 - cosine of two sign vectors = 2 x differing signs / s."""
    differing = F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda n, v: n + v)
    return F.lit(2.0) * differing / F.lit(float(s))


def exact_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """``event, i, j, d``: 1 - |common| / sqrt(|A| |B|) of word sets ``event, phase, word``, for
    phase pairs that share a word (all others are 1)."""
    size = lambda x, i, n: x.groupBy("event", F.col("phase").alias(i)).agg(F.count("*").cast("double").alias(n))
    common = a.select("event", F.col("phase").alias("i"), "word").join(b.select("event", F.col("phase").alias("j"), "word"), ["event", "word"]).groupBy("event", "i", "j").agg(F.count("*").alias("c"))
    return common.join(size(a, "i", "na"), ["event", "i"]).join(size(b, "j", "nb"), ["event", "j"]).select("event", "i", "j", (1 - F.col("c") / F.sqrt(F.col("na") * F.col("nb"))).alias("d"))
