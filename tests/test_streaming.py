import pytest
from pyspark.sql import functions as F

from phasewarp.operators import phases
from phasewarp.streaming import jobs


@pytest.fixture(scope="module")
def feed(spark, tmp_path_factory):
    """Events as ordered daily files; one file also holds rows moved four days back."""
    top = tmp_path_factory.mktemp("feed")
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").withColumn("day", phases.phase_of(F.col("ts"))).filter("day <= 10").persist()
    for k in range(1, 11):
        part = events.filter(F.col("day") == k).drop("day")
        part.coalesce(1).write.mode("append").parquet(str(top / "plain"))
    return events.drop("day"), str(top / "plain"), str(top)


def test_tumbling_counts_equal_batch(spark, feed):
    events, path, top = feed
    live = jobs.drain(jobs.word_counts(jobs.as_words(jobs.read_events(spark, path))), "counts", top, "update")
    got = {(r.day, r.event, r.medium, r.word): r.n for r in live.groupBy(F.col("window.start").cast("string").alias("day"), "event", "medium", "word").agg(F.max("freq").alias("n")).collect()}
    batch = jobs.as_words(events).groupBy(F.window("ts", "1 day"), "event", "medium", "word").agg(F.count("*").alias("n"))
    want = {(r.day, r.event, r.medium, r.word): r.n for r in batch.select(F.col("window.start").cast("string").alias("day"), "event", "medium", "word", "n").collect()}
    assert got == want


def test_resent_rows_count_once(spark, feed, tmp_path):
    events, path, _ = feed
    doubled = str(tmp_path / "twice")
    events.unionAll(events).coalesce(1).write.parquet(doubled)
    assert jobs.drain(jobs.deduplicated(jobs.read_events(spark, doubled)), "once", str(tmp_path)).count() == events.count()


def test_interval_join_equals_batch(spark, feed, tmp_path):
    events, path, _ = feed
    live = jobs.drain(jobs.followed(jobs.as_words(jobs.read_events(spark, path))), "followed", str(tmp_path))
    w = jobs.as_words(events)
    a, b = w.filter("medium = 'A'").alias("a"), w.filter("medium = 'B'").alias("b")
    want = a.join(b, F.expr("a.event = b.event AND a.word = b.word AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 2 HOURS")).count()
    assert live.count() == want


def test_micro_batches_realign(spark, feed, tmp_path):
    events, path, _ = feed
    q = jobs.realign(spark, jobs.as_words(jobs.read_events(spark, path, 5)), str(tmp_path), n=10)
    assert q.awaitTermination(240)
    assert {r.event for r in spark.read.parquet(str(tmp_path / "measures")).collect()} == {"0", "1", "2", "3"}
