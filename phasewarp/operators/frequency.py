"""Word counts per phase: the only shuffle that grows with the text, combined before it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEYS = ["event", "medium"]


def phase_words(records: DataFrame, count: str = "both") -> DataFrame:
    """``event, medium, phase, word, freq, rec_freq`` from records with ``phase`` and ``words``.

    ``count='occurrence'`` or ``'record'`` gives one of them as ``freq``; a record's own repeats
    are summed inside the row, so counting records needs no distinct.
    """
    keys = [*KEYS, "phase"]
    if count == "record":
        return records.select(*keys, F.explode(F.array_distinct("words")).alias("word")).groupBy(*keys, "word").agg(F.count("*").alias("freq"))
    tokens = records.select(*keys, F.explode("words").alias("word"))
    if count == "occurrence":
        return tokens.groupBy(*keys, "word").agg(F.count("*").alias("freq"))
    first = records.select(*keys, F.posexplode("words").alias("_at", "word"), F.col("words").alias("_w"))
    return first.groupBy(*keys, "word").agg(F.count("*").alias("freq"), F.sum((F.array_position("_w", F.col("word")) == F.col("_at") + 1).cast("long")).alias("rec_freq"))


def phase_records(records: DataFrame) -> DataFrame:
    return records.groupBy(*KEYS, "phase").agg(F.count("*").alias("n_records"))


def vocabulary(words: DataFrame, scope: list[str] | None = None) -> DataFrame:
    """``word, freq`` per scope (event and medium by default)."""
    return words.groupBy(*(scope or KEYS), "word").agg(F.sum("freq").alias("freq"))


def coarser(words: DataFrame, factor: int) -> DataFrame:
    """Counts of phases ``factor`` times as long; text is not read again."""
    phase = F.floor((F.col("phase") - 1) / factor).cast("int") + 1
    return words.groupBy(*KEYS, phase.alias("phase"), "word").agg(F.sum("freq").alias("freq"))
