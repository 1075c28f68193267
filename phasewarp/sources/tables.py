"""Sources: the given tables as records of two media, with planted or real clocks.

Records have the columns ``event, medium, record_id, ts, text`` and, where known, ``lang``.
"""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phasewarp.functions.text import strip_html

DAYS = 30
ORIGIN = "2024-01-01 00:00:00"
#: Shares of 1000 slots, a base per day and extras by day.
PROFILES = {
    "single": (10, {10: 300, 11: 200, 12: 120, 13: 80}),
    "multiple": (12, {2: 220, 6: 180, 13: 140, 20: 100}),
    "hybrid": (10, {4: 50, 8: 50, 12: 50, 16: 450, 20: 50, 24: 50}),
}
#: Profile on medium A, on medium B, and B's lag in days, by event.
SCENARIO = {
    "0": ("multiple", "multiple", 1), "1": ("single", "single", 0), "2": ("single", "single", 1),
    "3": ("multiple", "multiple", 2), "4": ("single", "hybrid", 0), "5": ("hybrid", "hybrid", 0),
    "6": ("multiple", "multiple", 0), "7": ("hybrid", "hybrid", 2), "8": ("single", "single", 3),
}
SHIFT_SCENARIO = {e: ("multiple", "multiple", 4) for e in SCENARIO}
PERIODIC_SCENARIO = {e: ("hybrid", "single", 2) for e in SCENARIO}
PAIR_SCENARIO = {e: ("single", "single", 1) for e in ("en", "fr", "de", "es")}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def profile_intervals(profile: str) -> list[tuple[int, int, int]]:
    """(day, first slot, end slot) of a profile."""
    base, extra = PROFILES[profile]
    ends = list(itertools.accumulate(base + extra.get(d, 0) for d in range(1, DAYS + 1)))
    return [(d, s, e) for d, s, e in zip(range(1, DAYS + 1), [0, *ends], ends)]


def _day_of(profile: str, slot: Column) -> Column:
    ends = F.array(*[F.lit(e) for _, _, e in profile_intervals(profile)])
    return F.size(F.filter(ends, lambda e: e <= slot)) + 1


def planted(records: DataFrame, scenario: dict, clock: str = "quota") -> DataFrame:
    """``ts`` by the scenario's profiles.  ``hash``: a slot from the key alone (map only);
    ``quota``: slots dealt evenly in key-hash order, so that the profile is met up to rounding."""
    key = F.col("record_id").cast("string")
    if clock == "hash":
        slotted = records.withColumn("_u", F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long") % 1000)
    else:
        by = Window.partitionBy("event", "medium")
        rank = F.row_number().over(by.orderBy(F.md5(key), "record_id"))
        slotted = records.withColumn("_c", F.count("*").over(by)).withColumn("_u", F.expr("0L")).withColumn("_r", rank)
        slotted = slotted.withColumn("_u", F.expr("((2 * _r - 1) * 1000) div (2 * _c)")).drop("_c", "_r")
    day = F.lit(None).cast("int")
    for (a, b, lag), events in itertools.groupby(sorted(scenario, key=lambda e: scenario[e]), key=lambda e: scenario[e]):
        hit = F.col("event").isin(*events)
        day = F.when(hit & (F.col("medium") == "A"), _day_of(a, F.col("_u"))).when(hit, F.least(F.lit(DAYS), _day_of(b, F.col("_u")) + lag)).otherwise(day)
    second = F.unix_timestamp(F.lit(ORIGIN)) + (day - 1) * 86400 + F.col("_u") % 24 * 3600
    return slotted.withColumn("ts", F.timestamp_seconds(second)).drop("_u")


def english_pair(spark: SparkSession, sf_dir: str, scenario: dict | None = None, clock: str = "quota") -> DataFrame:
    """English documents, nine events by source number, media by parity of the id."""
    docs = table(spark, sf_dir, "documents").filter("lang = 'en'")
    base = docs.select(
        (F.substring("source", 4, 9).cast("int") % 9).cast("string").alias("event"),
        F.when(F.col("doc_id") % 2 == 0, "A").otherwise("B").alias("medium"),
        F.col("doc_id").alias("record_id"), "text", "lang",
    )
    return planted(base, scenario or SCENARIO, clock)


def language_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event = language; documents against pages with their markup removed."""
    docs = table(spark, sf_dir, "documents").select(F.col("lang").alias("event"), F.lit("A").alias("medium"), F.col("doc_id").alias("record_id"), "text", "lang")
    lang = F.regexp_extract("url", r"^[a-z]+://[^/]+/([a-z]{2})/", 1)
    pages = table(spark, sf_dir, "pages").select(lang.alias("event"), F.lit("B").alias("medium"), F.col("page_id").alias("record_id"), strip_html(F.col("html")).alias("text"), lang.alias("lang"))
    return planted(docs.unionByName(pages).filter(F.col("event").isin(*PAIR_SCENARIO)), PAIR_SCENARIO)


def real_clock(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As P1 with the timestamps of ``events``, one event row per document."""
    docs, events = table(spark, sf_dir, "documents"), table(spark, sf_dir, "events")
    factor = events.agg(F.count("*").alias("e")).join(docs.agg(F.count("*").alias("d")), F.lit(True)).select(F.expr("e div d").alias("factor"))
    base = english_pair(spark, sf_dir).drop("ts").join(F.broadcast(factor), F.lit(True))
    return base.join(events.select("event_id", "ts"), F.col("record_id") * F.col("factor") == F.col("event_id")).drop("factor", "event_id")


def entity_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of ``events`` as short records; words from the type and the JSON value."""
    return table(spark, sf_dir, "events").select(
        (F.col("user_id") % 4).cast("string").alias("event"),
        F.when(F.floor(F.col("user_id") / 4) % 2 == 0, "A").otherwise("B").alias("medium"),
        F.col("event_id").alias("record_id"), "ts",
        F.concat_ws(" ", "event_type", F.concat(F.lit("k"), F.from_json("props", "k INT")["k"].cast("string"))).alias("text"),
    )


def order_ship_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """P5: parts by order date (A) against parts by ship date (B); event = supplier's region."""
    t = lambda n: table(spark, sf_dir, n)
    region = t("supplier").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", F.col("r_name").alias("event"))
    part = t("part").select("p_partkey", F.concat_ws(" ", "p_name", "p_brand", "p_type").alias("text"))
    lines = t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate").join(region, F.col("l_suppkey") == F.col("s_suppkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    key = (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("record_id")
    a = lines.join(t("orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey")).select("event", F.lit("A").alias("medium"), key, F.col("o_orderdate").alias("ts"), "text")
    return a.unionByName(lines.select("event", F.lit("B").alias("medium"), key, F.col("l_shipdate").alias("ts"), "text"))


def write_partitioned(df: DataFrame, path: str, *by: str) -> None:
    """Parquet with one folder per value of ``by``, rows dealt by the same keys first."""
    df.repartition(*by).write.mode("overwrite").partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, *by: str) -> None:
    """A table bucketed by the join keys, so that later joins on them do not shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *by).sortBy(*by).saveAsTable(name)


def read_json_records(spark: SparkSession, path: str) -> DataFrame:
    """Records extracted as JSON lines, with a fixed schema."""
    return spark.read.schema("event string, medium string, record_id long, ts timestamp, text string").json(path)
