"""Cut-off of unrelated words: power-law fit, median rank, threshold, filter."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from phasewarp.sources.lineage import cut

SLACK = 1e-9


def ranked(vocab: DataFrame, scope: list[str]) -> DataFrame:
    by = Window.partitionBy(*scope).orderBy(F.desc("freq"), "word")
    return vocab.withColumn("rank", F.row_number().over(by))


def ranked_by_range(vocab: DataFrame, scope: list[str], parts: int = 64) -> DataFrame:
    """The same ranks in two passes for vocabularies beyond one task: a range sort, one count per
    range and scope, and local ranks on top of the counts before.  The range number is kept in a
    checkpoint, because it must not change between the passes."""
    ranges = vocab.repartitionByRange(parts, *scope, F.desc("freq"), "word").withColumn("_part", F.spark_partition_id())
    ranges = cut(ranges)
    sizes = ranges.groupBy(*scope, "_part").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(*scope).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(*scope, "_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    local = Window.partitionBy(*scope, "_part").orderBy(F.desc("freq"), "word")
    return ranges.join(starts, [*scope, "_part"]).withColumn("rank", (F.col("_start") + F.row_number().over(local)).cast("int")).drop("_part", "_start")


def fit_power_law(ranks: DataFrame, scope: list[str]) -> DataFrame:
    """``alpha, h, vocab_size`` of freq = h rank^-alpha by regression of logarithms."""
    x, y = F.ln(F.col("rank").cast("double")), F.ln(F.col("freq").cast("double"))
    return ranks.groupBy(*scope).agg(
        (-F.regr_slope(y, x)).alias("alpha"), F.exp(F.regr_intercept(y, x)).alias("h"), F.count("*").alias("vocab_size")
    )


def median_rank(fit: DataFrame, support: str = "auto") -> DataFrame:
    """``r_half`` and ``regime``.  ``infinite``: 2^(1/(alpha-1)), for alpha > 1 only; ``truncated``:
    the median over ranks 1..V; ``auto``: the first where it is defined and within V."""
    a, v = F.col("alpha"), F.col("vocab_size").cast("double")
    infinite = F.when(a > 1, F.pow(F.lit(2.0), 1 / (a - 1)))
    cut = F.when(F.abs(a - 1) < 1e-12, F.sqrt(v)).otherwise(F.pow((1 + F.pow(v, 1 - a)) / 2, 1 / (1 - a)))
    if support == "infinite":
        return fit.withColumn("r_half", infinite).withColumn("regime", F.lit("infinite"))
    if support == "truncated":
        return fit.withColumn("r_half", cut).withColumn("regime", F.lit("truncated"))
    use = F.coalesce(infinite <= v, F.lit(False))
    return fit.withColumn("r_half", F.when(use, infinite).otherwise(cut)).withColumn("regime", F.when(use, "infinite").otherwise("truncated"))


def threshold(fit: DataFrame, fixed: float | None = None) -> DataFrame:
    """``th``: the fitted frequency at the median rank, or a fixed one."""
    if fixed is not None:
        return fit.withColumn("th", F.lit(float(fixed))).withColumn("regime", F.lit("fixed"))
    return fit.withColumn("th", F.col("h") * F.pow("r_half", -F.col("alpha")))


def kept_words(ranks: DataFrame, cutoff: DataFrame, scope: list[str], cut: str = "auto", at_least: int = 2, most: int | None = None) -> DataFrame:
    """Words that pass: ``scope, word, freq, rank, regime``.

    ``frequency``: freq >= th; ``rank``: rank <= r_half; ``auto``: the first, or the second where
    it would keep fewer than ``at_least`` words.  All that pass stay, unless a caller asks for the
    ``most`` first of them by rank.  The cut-off has one row per series, which is what is broadcast.
    """
    joined = ranks.join(F.broadcast(cutoff), scope)
    by_freq = F.col("freq") >= F.col("th") * (1 - SLACK)
    by_rank = F.col("rank") <= F.greatest(F.col("r_half"), F.lit(float(at_least)))
    if cut == "frequency":
        chosen = by_freq
    elif cut == "rank":
        joined, chosen = joined.withColumn("regime", F.lit("rank")), by_rank
    else:
        # freq falls with rank, so "at least k words pass" is "the k-th word passes"
        kth = joined.groupBy(*scope).agg(F.sum((by_freq & (F.col("rank") <= at_least)).cast("int")).alias("_pass"))
        joined = joined.join(F.broadcast(kth), scope)
        enough = F.col("_pass") >= at_least
        joined = joined.withColumn("regime", F.when(enough, F.col("regime")).otherwise("rank"))
        chosen = F.when(enough, by_freq).otherwise(by_rank)
    if most is None:
        return joined.filter(chosen).select(*scope, "word", "freq", "rank", "regime")
    cap = F.when((F.col("rank") == most) & chosen, 1)
    capped = joined.groupBy(*scope).agg(F.max(cap).alias("_cap"))
    return (
        joined.filter(chosen & (F.col("rank") <= most))
        .join(F.broadcast(capped), scope)
        .withColumn("regime", F.when(F.col("_cap") == 1, "capped").otherwise(F.col("regime")))
        .select(*scope, "word", "freq", "rank", "regime")
    )


def apply(words: DataFrame, kept: DataFrame, scope: list[str]) -> DataFrame:
    """Phase words that pass; broadcast or joined by size."""
    return words.join(kept.select(*scope, "word"), [*scope, "word"], "left_semi")


def reduction(vocab: DataFrame, kept: DataFrame, scope: list[str]) -> DataFrame:
    """Words and word pairs before and after."""
    pairs = lambda n: n * (n - 1) / 2
    before = vocab.groupBy(*scope).agg(F.count("*").alias("n_words"))
    after = kept.groupBy(*scope).agg(F.count("*").alias("n_kept"))
    return before.join(after, scope, "left").fillna(0, ["n_kept"]).withColumn("pair_ratio", pairs(F.col("n_words")) / F.nullif(pairs(F.col("n_kept")), F.lit(0.0)))
