"""Popularity series: the semantic weight, its baselines, normalisation, word stream."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from phasewarp.operators import cutoff, frequency, phases, similarity, wordrank
from phasewarp.sources.lineage import cut

KEYS = ["event", "medium", "phase"]


@dataclass(frozen=True)
class SwpConfig:
    """Parameters of the semantic-weight popularity; defaults are the published ones."""

    n_phases: int | None = 30
    scope: tuple[str, ...] = ("event", "medium")
    cut: str = "auto"
    support: str = "auto"
    th: float | None = None
    keep_at_least: int = 2
    max_vocab: int | None = None
    beta: float = similarity.BETA
    gamma: float = similarity.GAMMA
    theta: float = wordrank.THETA
    tol: float = 1e-9
    max_iter: int = 200
    teleport: str = "phase"
    total: str = "kept"
    compensation: str = "printed"
    extra: dict = field(default_factory=dict)


def word_popularity(words: DataFrame, weights: DataFrame) -> DataFrame:
    """freq x weight; words without a weight count 0."""
    return words.join(weights.select(*KEYS, "word", "weight"), [*KEYS, "word"], "left").withColumn("weight", F.coalesce("weight", F.lit(0.0))).withColumn("pop", F.col("freq") * F.col("weight"))


def phase_popularity(word_pop: DataFrame) -> DataFrame:
    return word_pop.groupBy(*KEYS).agg(F.sum("pop").alias("pop"))


def normalise(series: DataFrame) -> DataFrame:
    """``pop_norm``: shares that sum to one per event and medium; an all-zero series stays zero."""
    total = F.sum("pop").over(Window.partitionBy("event", "medium"))
    return series.withColumn("pop_norm", F.coalesce(F.col("pop") / F.nullif(total, F.lit(0.0)), F.lit(0.0)))


def _series(raw: DataFrame, n: int | None) -> DataFrame:
    return normalise(phases.densify(raw.select(*KEYS, F.col("pop").cast("double").alias("pop")), n))


def naive_series(words: DataFrame, n: int | None = 30) -> DataFrame:
    return _series(words.groupBy(*KEYS).agg(F.sum("freq").alias("pop")), n)


def tfidf_series(words: DataFrame, records: DataFrame, n: int | None = 30) -> DataFrame:
    """freq x (1 + ln(records / records with the word)) within the phase."""
    weighed = words.join(records, KEYS).withColumn("pop", F.col("freq") * (1 + F.ln(F.col("n_records").cast("double") / F.col("rec_freq"))))
    return _series(phase_popularity(weighed), n)


def volume_series(records: DataFrame, n: int | None = 30) -> DataFrame:
    return _series(records.groupBy(*KEYS).agg(F.count("*").alias("pop")), n)


def weights(ranks: DataFrame, totals: DataFrame, compensation: str = "printed") -> DataFrame:
    """Weight of a contributive word: its rank, compensated by the number of contributive words
    (divided as printed, multiplied with ``count``), times the phase's total frequency."""
    n = F.count("*").over(Window.partitionBy(*KEYS)).cast("double")
    scaled = F.col("tr") / n if compensation == "printed" else F.col("tr") * n
    return ranks.withColumn("_s", scaled).join(totals, KEYS).select(*KEYS, "word", "tr", (F.col("_s") * F.col("total")).alias("weight"))


@dataclass
class Swp:
    """Stages of one run; contributive words are those with a rank."""

    kept: DataFrame
    kept_words: DataFrame
    links: DataFrame
    contributive: DataFrame
    ranks: DataFrame
    weights: DataFrame
    word_pop: DataFrame
    series: DataFrame


def semantic_weight(words: DataFrame, vectors: DataFrame, cfg: SwpConfig = SwpConfig(), strategy: str = "series") -> Swp:
    """From phase words and word vectors to the normalised series, with every stage on the way.

    The words left by the cut-off and their ranks are small and read by several stages, so their
    lineage is cut there.  Word pairs become rows (``links``) only where a caller reads them, and
    with the strategies ``grouped`` and ``joined``.
    """
    scope = list(cfg.scope)
    ranks_ = cutoff.ranked(frequency.vocabulary(words, scope), scope)
    fit = cutoff.threshold(cutoff.median_rank(cutoff.fit_power_law(ranks_, scope), cfg.support), cfg.th)
    kept = cutoff.kept_words(ranks_, fit, scope, cfg.cut, cfg.keep_at_least, cfg.max_vocab)
    left = cut(cutoff.apply(words, kept, scope))
    both = left.select("event", "medium", "word").distinct()
    links = similarity.edges(both, vectors, ["event", "medium"], cfg.beta, cfg.gamma)
    if strategy == "series":
        tr = wordrank.rank_words(left, vectors, cfg.beta, cfg.gamma, cfg.theta, cfg.tol, cfg.max_iter, cfg.teleport)
    else:
        graph = similarity.phase_edges(links, left)
        ranked = wordrank.rank if strategy == "grouped" else wordrank.rank_joined
        tr = ranked(graph, cfg.theta, cfg.tol, cfg.max_iter, cfg.teleport)
    tr = cut(tr)
    totals = (left if cfg.total == "kept" else words).groupBy(*KEYS).agg(F.sum("freq").alias("total"))
    w = weights(tr, totals, cfg.compensation)
    pops = word_popularity(left, w)
    # phases of words that were all cut off stay on the grid
    raw = phase_popularity(pops)
    seen = words.select("event", "medium").distinct()
    series = normalise(phases.densify(seen.join(raw, ["event", "medium"], "left").withColumn("phase", F.coalesce("phase", F.lit(1))), cfg.n_phases))
    return Swp(kept, left, links, tr.select(*KEYS, "word"), tr, w, pops, series.select(*KEYS, "pop", "pop_norm"))


def semantic_weight_series(words: DataFrame, vectors: DataFrame, cfg: SwpConfig = SwpConfig()) -> DataFrame:
    return semantic_weight(words, vectors, cfg).series


def word_stream(word_pop: DataFrame, top: int = 20, layout: str = "weighted_wiggle") -> DataFrame:
    """Bands ``y0, y1`` of the ``top`` words of each series, stacked by word order in each phase.

    ``zero``: the stack stands on 0.  ``weighted_wiggle``: its base moves so that the slopes of
    the layers, weighted by their widths, are least.
    """
    series = ["event", "medium"]
    order = Window.partitionBy(*series).orderBy(F.desc(F.round("_all", 6)), "word")  # ties as in any engine
    best = word_pop.groupBy(*series, "word").agg(F.sum("pop").alias("_all")).withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= top).drop("_all")
    at = word_pop.select(*series, "phase").distinct()
    full = best.join(at, series).join(word_pop.select(*KEYS, "word", "pop"), [*KEYS, "word"], "left").withColumn("pop", F.coalesce("pop", F.lit(0.0)))
    over = Window.partitionBy(*KEYS)
    below = over.orderBy("rank").rowsBetween(Window.unboundedPreceding, -1)
    stacked = full.withColumn("_low", F.coalesce(F.sum("pop").over(below), F.lit(0.0)))
    if layout == "zero":
        based = stacked.withColumn("_base", F.lit(0.0))
    else:
        time = Window.partitionBy(*series, "word").orderBy("phase")
        moved = stacked.withColumn("_d", F.col("pop") - F.coalesce(F.lag("pop").over(time), F.lit(0.0)))
        moved = moved.withColumn("_under", F.coalesce(F.sum("_d").over(below), F.lit(0.0)))
        slope = F.sum((F.col("_under") + F.col("_d") / 2) * F.col("pop")) / F.nullif(F.sum("pop"), F.lit(0.0))
        base = moved.groupBy(*KEYS).agg((-F.coalesce(slope, F.lit(0.0))).alias("_s")).withColumn("_base", F.sum("_s").over(Window.partitionBy(*series).orderBy("phase")))
        based = stacked.join(base.select(*KEYS, "_base"), KEYS)
    total = F.sum("pop").over(over)
    return based.select(*KEYS, "word", "rank", "pop", F.coalesce(F.col("pop") / F.nullif(total, F.lit(0.0)), F.lit(0.0)).alias("share"), (F.col("_base") + F.col("_low")).alias("y0"), (F.col("_base") + F.col("_low") + F.col("pop")).alias("y1"))
