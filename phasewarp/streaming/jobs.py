"""Structured Streaming forms: counts live, windows, sessions, bursts, dedup, joins, re-alignment.

Each function takes a streaming (or batch) DataFrame and returns one; :func:`drain` runs a query
until the source is exhausted, which is how stream and batch are compared.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from phasewarp.operators import alignment, metrics, phases, popularity

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def as_words(events: DataFrame) -> DataFrame:
    """Rows of the event stream as single words of two media."""
    return events.select("event_id", "ts", F.when(F.floor(F.col("user_id") / 4) % 2 == 0, "A").otherwise("B").alias("medium"), (F.col("user_id") % 4).cast("string").alias("event"), F.col("event_type").alias("word"))


def word_counts(words: DataFrame, delay: str = "1 day", length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Counts per window, event, medium and word; rows later than the watermark are dropped."""
    return words.withWatermark("ts", delay).groupBy(F.window("ts", length, slide or length), "event", "medium", "word").agg(F.count("*").alias("freq"))


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Re-sent records once, with state bounded by the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def followed(words: DataFrame, within: str = "2 hours", delay: str = "1 day") -> DataFrame:
    """A word on medium A followed within ``within`` by the same word of the event on B."""
    a = words.filter("medium = 'A'").select("event", "word", F.col("ts").alias("ts_a"), F.col("event_id").alias("id_a")).withWatermark("ts_a", delay)
    b = words.filter("medium = 'B'").select(F.col("event").alias("event_b"), F.col("word").alias("word_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("id_b")).withWatermark("ts_b", delay)
    near = F.expr(f"event = event_b AND word = word_b AND ts_b >= ts_a AND ts_b <= ts_a + INTERVAL {within}")
    return a.join(b, near).select("event", "word", "id_a", "id_b", "ts_a", "ts_b")


def weighted(words: DataFrame, weights: DataFrame) -> DataFrame:
    """Stream joined with the kept words and weights of the last batch fit (one row per word)."""
    return words.join(F.broadcast(weights.select("word", "weight")), "word")


class BurstProcessor(StatefulProcessor):
    """Per event and medium: the last closed phases' counts; alerts when one exceeds ``factor``
    times the mean of the ``window`` before it."""

    def __init__(self, window: int = 3, factor: float = 2.0):
        self.window, self.factor = window, factor

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("trailing", "phases array<int>, counts array<long>")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        held = self.state.get()
        counts = dict(zip(held[0], held[1])) if held is not None else {}
        for pdf in rows:
            for phase, n in zip(pdf["phase"].tolist(), pdf["n"].tolist()):
                counts[phase] = n  # update mode: the newest count of a phase replaces the older
        alerts = []
        for phase in sorted(counts):
            before = [counts[p] for p in range(phase - self.window, phase) if p in counts]
            if len(before) == self.window and counts[phase] > self.factor * sum(before) / self.window:
                alerts.append((*key, phase, counts[phase], sum(before) / self.window))
        keep = sorted(counts)[-(self.window + 2) :]
        self.state.update((keep, [counts[p] for p in keep]))
        yield pd.DataFrame(alerts, columns=["event", "medium", "phase", "n", "trailing"])

    def close(self) -> None:
        pass


def burst_alerts(phase_counts: DataFrame, window: int = 3, factor: float = 2.0) -> DataFrame:
    """Alerts from a stream of ``event, medium, phase, n``."""
    return phase_counts.groupBy("event", "medium").transformWithStateInPandas(
        statefulProcessor=BurstProcessor(window, factor), outputStructType="event string, medium string, phase int, n long, trailing double", outputMode="Update", timeMode="None"
    )


def realign(spark: SparkSession, words: DataFrame, folder: str, n: int = 30, method: str = "wdtw"):
    """A ``foreachBatch`` query: each micro-batch appends its phase counts and re-aligns the whole
    series so far; the measures of the newest state overwrite ``folder/measures``."""

    def step(batch: DataFrame, number: int) -> None:
        counts = phases.assign(batch, n=n).groupBy("event", "medium", "phase").agg(F.count("*").alias("pop"))
        counts.write.mode("overwrite").parquet(f"{folder}/counts/batch={number}")
        all_counts = spark.read.parquet(f"{folder}/counts").groupBy("event", "medium", "phase").agg(F.sum("pop").cast("double").alias("pop"))
        series = popularity.normalise(phases.densify(all_counts, n)).persist()
        aligned = alignment.align(alignment.pack(series), method, engine="arrow")
        metrics.summary(alignment.matches(aligned), series).write.mode("overwrite").parquet(f"{folder}/measures")
        series.unpersist()

    return words.writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()


def drain(stream: DataFrame, name: str, folder: str, mode: str = "append", limit: float = 300) -> DataFrame:
    """All that a stream gives, as an in-memory table, once its source is exhausted."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/{name}").trigger(availableNow=True).start()
    if not q.awaitTermination(limit):
        q.stop()
        raise TimeoutError(f"stream {name} did not finish")
    return stream.sparkSession.table(name)
