"""Experiment workloads, re-expressed on the given tables, with their SQL twins."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from phasewarp.functions import text
from phasewarp.operators import alignment, diagnostics, frequency, metrics, phases, popularity
from phasewarp.operators.alignment import METHODS
from phasewarp.plans import sqltext as s
from phasewarp.plans.queries import (
    ALL, CALENDAR, DEFECTS, GRADES, NAIVE, PEAKS, RECALL, ROUNDS, SCOPE, TFIDF, calendar, found_matches, graded, held, measured, naive_sql, p1, p1_naive, p1_swp,
    p1_words, packed_swp, query, r6, summary_sql, swp_cells, vectors_of,
)
from phasewarp.sources import tables
from phasewarp.sources.tables import PERIODIC_SCENARIO, SHIFT_SCENARIO, table

CATALOGUE = "SELECT event, medium, count(*) AS n_records, CAST(sum(strlen(text)) AS BIGINT) AS n_bytes, min(phase) AS d_from, max(phase) AS d_to FROM timed GROUP BY event, medium"


def _catalogue(records):
    return phases.assign(records, n=30).groupBy(*SCOPE).agg(F.count("*").alias("n_records"), F.sum(F.octet_length("text")).alias("n_bytes"), F.min("phase").alias("d_from"), F.max("phase").alias("d_to"))


query("catalogue", s.with_(*s.clocked()) + CATALOGUE)(lambda spark, d: _catalogue(tables.english_pair(spark, d)))
query("catalogue_p2", s.with_(*s.PAIRS) + CATALOGUE)(lambda spark, d: _catalogue(tables.language_pair(spark, d)))
query("pair_epts", s.with_(*s.PAIRS, *s.tokens(), *NAIVE, *s.series("nv0")) + f"SELECT event, medium, phase, {s.r('pop_norm')} AS pop_norm FROM epts")(
    lambda spark, d: popularity.naive_series(frequency.phase_words(text.prepare(phases.assign(tables.language_pair(spark, d), n=30)))).select(*popularity.KEYS, *r6("pop_norm"))
)


# Dated sub-events as peaks, by the semantic weight (th = 10) and both baselines
def _w3_series(spark, d):
    records = p1(spark, d)
    words = held(frequency.phase_words(records))
    swp = p1_swp(spark, d, words=words).series
    return {"swp": swp, "naive": popularity.naive_series(words), "tfidf": popularity.tfidf_series(words, frequency.phase_records(records))}


def _renamed(parts: list[str], old: str, new: str) -> list[str]:
    return [p.replace(old, new) for p in parts]


def _by_method(tail_parts: list[str], tail: str, extra: list[str] = []) -> str:
    sources = {"swp": "pp", "naive": "nv0", "tfidf": "tf0"}
    head = [*s.base(), *s.fitted(fixed=10.0), *s.edges(), *s.ranks(), *s.swp(), *NAIVE, *TFIDF, *extra]
    full = list(head)
    for m, src in sources.items():
        full += [p.replace("FROM " + src + ")", "FROM pw)") if k == 0 else p for k, p in enumerate(s.series(src, name=f"epts_{m}"))]
        full += [p.replace("pk AS", f"pk_{m} AS").replace("FROM epts)", f"FROM epts_{m})") for p in tail_parts]
    return s.with_(*full) + " UNION ALL ".join(f"SELECT '{m}' AS method, * FROM (" + tail.replace("FROM pk)", f"FROM pk_{m})").replace("FROM epts", f"FROM epts_{m}") + ")" for m in sources)


@query("w3_peaks", _by_method(PEAKS, RECALL, [CALENDAR]))
def _(spark, d):
    out, cal = None, calendar(spark)
    for m, series in _w3_series(spark, d).items():
        one = diagnostics.peak_recall(diagnostics.peaks(series), cal).select(F.lit(m).alias("method"), *SCOPE, "n_events", "n_hit", "recall")
        out = one if out is None else out.unionByName(one)
    return out


@query("w4_burst", " UNION ALL ".join("SELECT * FROM (" + s.with_(*s.full_swp(fixed=t)) + f"SELECT {t}::DOUBLE AS th, event, medium, phase, {s.r('pop_norm - coalesce(lag(pop_norm) OVER (PARTITION BY event, medium ORDER BY phase), 0)')} AS rise FROM epts)" for t in (5.0, 10.0, 20.0)))
def _(spark, d):
    words, out = p1_words(spark, d), None
    for t in (5.0, 10.0, 20.0):
        rise = diagnostics.burst_gain(p1_swp(spark, d, replace(ROUNDS, th=t), words=words).series)
        one = rise.select(F.lit(t).alias("th"), *popularity.KEYS, *r6("rise"))
        out = one if out is None else out.unionByName(one)
    return out


# Six days of the same base records of an event, with growing unrelated noise
#: Noise records per day over 50 thousand base records.
NOISE = (0.0, 0.02126, 0.0447, 0.07014, 0.09378, 0.12052)
NOISE_SQL = [
    "base AS (SELECT CAST(CAST(substr(source, 4) AS INT) % 9 AS VARCHAR) AS event, doc_id, text FROM documents WHERE lang = 'en')",
    "bn AS (SELECT event, count(*) AS n FROM base GROUP BY event)",
    "ratio(phase, share) AS (VALUES " + ", ".join(f"({k + 1}, {v}::DOUBLE)" for k, v in enumerate(NOISE)) + ")",
    "want AS (SELECT event, phase, CAST(round(n * share) AS BIGINT) AS n FROM bn CROSS JOIN ratio)",
    "span AS (SELECT *, coalesce(sum(n) OVER (PARTITION BY event ORDER BY phase ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS lo FROM want)",
    "noise AS (SELECT doc_id, text, row_number() OVER (ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id) AS rn FROM documents WHERE lang <> 'en')",
    """timed AS (SELECT event, 'A' AS medium, phase, doc_id AS record_id, text, 'en' AS lang FROM base CROSS JOIN ratio
  UNION ALL SELECT event, 'A', phase, doc_id, text, 'x' FROM span JOIN noise ON rn > lo AND rn <= lo + n)""",
]


def noise_corpus(spark, d):
    """Records with ``event, medium, phase``: each day the base of the event and its own noise."""
    docs = table(spark, d, "documents").select("doc_id", "text", "lang", "source")
    base = docs.filter("lang = 'en'").select((F.substring("source", 4, 9).cast("int") % 9).cast("string").alias("event"), F.col("doc_id").alias("record_id"), "text")
    from pyspark.sql import Window

    ratio = spark.createDataFrame([(k + 1, v) for k, v in enumerate(NOISE)], "phase int, share double")
    want = base.groupBy("event").agg(F.count("*").alias("n")).join(F.broadcast(ratio), F.lit(True)).withColumn("n", F.round(F.col("n") * F.col("share")).cast("long"))
    before = Window.partitionBy("event").orderBy("phase").rowsBetween(Window.unboundedPreceding, -1)
    spans = want.withColumn("lo", F.coalesce(F.sum("n").over(before), F.lit(0))).filter("n > 0")
    slots = spans.select("event", "phase", F.explode(F.sequence(F.col("lo") + 1, F.col("lo") + F.col("n"))).alias("rn"))
    order = Window.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id")
    # only as many noise records as the slots ask for are numbered
    most = spans.agg(F.coalesce(F.max(F.col("lo") + F.col("n")), F.lit(0))).first()[0]
    first = docs.filter("lang <> 'en'").orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(int(most))
    noise = first.withColumn("rn", F.row_number().over(order).cast("long")).select("rn", F.col("doc_id").alias("record_id"), "text")
    days = base.withColumn("phase", F.explode(F.sequence(F.lit(1), F.lit(len(NOISE)))))
    added = slots.join(noise, "rn")
    cols = ["event", F.lit("A").alias("medium"), "phase", "record_id", "text"]
    return days.select(*cols).unionByName(added.select(*cols))


query("w5_noise_corpus", s.with_(*NOISE_SQL) + "SELECT event, CAST(phase AS INT) AS phase, count(*) AS n, CAST(sum(record_id) AS BIGINT) AS ids FROM timed GROUP BY event, phase")(
    lambda spark, d: noise_corpus(spark, d).groupBy("event", "phase").agg(F.count("*").alias("n"), F.sum("record_id").alias("ids"))
)


def w5_series(spark, d):
    records = held(text.prepare(noise_corpus(spark, d), stop="all"))
    words = held(frequency.phase_words(records))
    cfg = popularity.SwpConfig(n_phases=6, cut="rank", support="truncated", tol=0.0, max_iter=30)
    return {
        "swp": popularity.semantic_weight_series(words, vectors_of(spark, d, words), cfg),
        "naive": popularity.naive_series(words, 6),
        "tfidf": popularity.tfidf_series(words, frequency.phase_records(records), 6),
    }


@query("w5_flatness")
def _(spark, d):
    out = None
    for m, series in w5_series(spark, d).items():
        one = diagnostics.flatness(series).select(F.lit(m).alias("method"), *SCOPE, *r6("max_dev", "cv"))
        out = one if out is None else out.unionByName(one)
    return out


# Defects of methods on the noisy clock
def _defects(spark, d, methods):
    return diagnostics.defects(found_matches(spark, d, methods, clock="hash")).select("event", "method", "n_singular", "n_far")


for _name, _ms in (("w6_singular", ["dtw", "dtw_bias", "wdtw", "wcw"]), ("w7_far", ["ddtw", "ddtw_bias", "wddtw", "cw", "wcw"])):
    query(_name, s.with_(*swp_cells(*_ms, clock="hash"), *s.warped(), *DEFECTS) + "SELECT event, method, n_singular, n_far FROM df")(lambda spark, d, m=_ms: _defects(spark, d, m))

_GRADES = s.with_(*swp_cells(*ALL, clock="hash"), *s.warped(), *DEFECTS, *GRADES)
query("w8_grades", _GRADES + "SELECT event, method, grade FROM gr")(lambda spark, d: graded(spark, d).select("event", "method", "grade"))
WCW = ["wcw_1", "wcw", "wcw_3"]
query("w9_settings", summary_sql(swp_cells(*WCW), ["psi_s", "psi_a", "lead_a"]))(lambda spark, d: measured(spark, d, WCW).select("event", "method", *r6("psi_s", "psi_a", "lead_a")))

# Hours instead of days
HOURLY = """vol AS (SELECT '0' AS event, CASE WHEN event_type IN ('view', 'click') THEN 'A' ELSE 'B' END AS medium, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01')) AS BIGINT) // 3600 + 1 AS phase, count(*) AS pop
  FROM events WHERE event_type IN ('view', 'click', 'signup', 'purchase') GROUP BY ALL)"""


def hourly(spark, d, days: int = 30):
    e = table(spark, d, "events").filter(F.col("event_type").isin("view", "click", "signup", "purchase"))
    records = e.select(F.lit("0").alias("event"), F.when(F.col("event_type").isin("view", "click"), "A").otherwise("B").alias("medium"), "ts")
    return popularity.volume_series(phases.assign(records, "hour", n=24 * days), 24 * days)


query("w10_hourly", s.with_(HOURLY, *s.series("vol", 720)) + f"SELECT event, medium, phase, {s.r('pop_norm', 8)} AS pop_norm FROM epts")(lambda spark, d: hourly(spark, d).select(*popularity.KEYS, F.round("pop_norm", 8).alias("pop_norm")))


@query("w10_hourly_align")
def _(spark, d):
    """720 hourly phases, banded: path statistics and measures."""
    series = held(hourly(spark, d))
    aligned = held(alignment.align(alignment.pack(series), "wdtw", engine="arrow", band=True))
    return metrics.path_stats(aligned).join(metrics.summary(alignment.matches(aligned), series).drop("n_matches"), ["event", "method"])


# Measures by event
query("w11_psi_a", summary_sql(swp_cells("wcw_1"), ["psi_a"]))(lambda spark, d: measured(spark, d, ["wcw_1"]).select("event", "method", *r6("psi_a")))
query("w12_min_psi_s", "SELECT method, arg_min(event, psi_s) AS event, min(psi_s) AS psi_s FROM (" + summary_sql(swp_cells("wcw_1"), ["psi_s"]) + ") GROUP BY method")(
    lambda spark, d: measured(spark, d, ["wcw_1"]).select("event", "method", *r6("psi_s")).groupBy("method").agg(F.min_by("event", "psi_s").alias("event"), F.min("psi_s").alias("psi_s"))
)


def _lead_rank(df):
    from pyspark.sql import Window

    return df.select("event", "method", *r6("lead_a")).withColumn("place", F.rank().over(Window.partitionBy("method").orderBy(F.desc("lead_a"))))


query("w13_lead_rank", "SELECT *, rank() OVER (PARTITION BY method ORDER BY lead_a DESC) AS place FROM (" + summary_sql(swp_cells("wcw", "wcw_1"), ["lead_a"]) + ")")(
    lambda spark, d: _lead_rank(measured(spark, d, ["wcw", "wcw_1"]))
)
PERIODIC = s.with_(*naive_sql(PERIODIC_SCENARIO), *PEAKS)


@query("w14_periodic", PERIODIC + "SELECT event, medium, phase, peak_rank FROM (SELECT *, row_number() OVER (PARTITION BY event, medium ORDER BY pop_norm DESC, phase) AS peak_rank FROM pk) WHERE peak_rank <= 6")
def _(spark, d):
    return diagnostics.top_peaks(p1_naive(spark, d, PERIODIC_SCENARIO), 6).select(*popularity.KEYS, "peak_rank")


query("w16_shift", summary_sql(swp_cells("dtw", "cw", "wcw", scenario=SHIFT_SCENARIO), ["lead_a"]))(lambda spark, d: measured(spark, d, ["dtw", "cw", "wcw"], SHIFT_SCENARIO).select("event", "method", *r6("lead_a")))

# Word stream
_STREAM = [
    "best AS (SELECT event, medium, word, rank FROM (SELECT *, row_number() OVER (PARTITION BY event, medium ORDER BY round(pops, 6) DESC, word) AS rank FROM (SELECT event, medium, word, sum(pop) AS pops FROM wp GROUP BY event, medium, word)) WHERE rank <= 20)",
    "full0 AS (SELECT b.*, p.phase, coalesce(w.pop, 0.0::DOUBLE) AS pop FROM best b JOIN (SELECT DISTINCT event, medium, phase FROM wp) p USING (event, medium) LEFT JOIN wp w USING (event, medium, phase, word))",
]


def _stream(spark, d):
    pops = p1_swp(spark, d).word_pop
    return popularity.word_stream(pops)


query("word_stream")(lambda spark, d: _stream(spark, d))
query("word_stream_topk", s.with_(*s.full_swp(), *_STREAM) + "SELECT event, medium, word, CAST(rank AS INT) AS rank FROM best")(lambda spark, d: _stream(spark, d).select(*SCOPE, "word", "rank").distinct())

# Other carriers
REGION = "reg AS (SELECT s_suppkey, r_name AS event FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
PARTS = "ptx AS (SELECT p_partkey, concat_ws(' ', p_name, p_brand, p_type) AS text FROM part)"
MONTH = lambda c: f"(year({c}) - 1992) * 12 + month({c})"
TPCH = [REGION, PARTS, f"""timed AS (SELECT event, 'A' AS medium, {MONTH('o_orderdate')} AS phase, l_orderkey * 8 + l_linenumber AS record_id, text, 'x' AS lang
  FROM lineitem JOIN reg ON l_suppkey = s_suppkey JOIN ptx ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey
  UNION ALL SELECT event, 'B', {MONTH('l_shipdate')}, l_orderkey * 8 + l_linenumber, text, 'x' FROM lineitem JOIN reg ON l_suppkey = s_suppkey JOIN ptx ON l_partkey = p_partkey)"""]  # fmt: skip


def order_ship_words(spark, d):
    records = phases.assign(tables.order_ship_pair(spark, d), "month", "1992-01-01 00:00:00", 96)
    return frequency.phase_words(text.prepare(records, stop=None).withColumn("words", F.filter("words", lambda w: F.length(w) >= 2)))


query("w17_orders_vs_ship", s.with_(*TPCH, *s.tokens("lang"), *NAIVE, *s.series("nv0", 96)) + f"SELECT event, medium, phase, {s.r('pop_norm', 8)} AS pop_norm FROM epts")(
    lambda spark, d: popularity.naive_series(order_ship_words(spark, d), 96).select(*popularity.KEYS, F.round("pop_norm", 8).alias("pop_norm"))
)
ENTITY = [
    """timed AS (SELECT CAST(user_id % 4 AS VARCHAR) AS event, CASE WHEN (user_id // 4) % 2 = 0 THEN 'A' ELSE 'B' END AS medium,
  CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01')) AS BIGINT) // 86400 + 1 AS phase, event_id AS record_id, concat_ws(' ', event_type, 'k' || CAST(json_extract_string(props, '$.k') AS VARCHAR)) AS text, 'x' AS lang FROM events)"""
]


def entity_words(spark, d):
    records = phases.assign(tables.entity_records(spark, d), n=30)
    return frequency.phase_words(text.prepare(records, stop=None).withColumn("words", F.filter("words", lambda w: F.length(w) >= 2)))


query("w18_events_epts", s.with_(*ENTITY, *s.tokens("lang"), *NAIVE, *s.series("nv0")) + f"SELECT event, medium, phase, {s.r('pop_norm', 8)} AS pop_norm FROM epts")(
    lambda spark, d: popularity.naive_series(entity_words(spark, d)).select(*popularity.KEYS, F.round("pop_norm", 8).alias("pop_norm"))
)


@query("real_clock_epts", s.with_(*s.clocked(), "fac AS (SELECT (SELECT count(*) FROM events) // (SELECT count(*) FROM documents) AS f)",
                                  "vol AS (SELECT event, medium, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01')) AS BIGINT) // 86400 + 1 AS phase, count(*) AS pop FROM rec CROSS JOIN fac JOIN events ON event_id = record_id * f GROUP BY ALL)", *s.series("vol"))
       + f"SELECT event, medium, phase, {s.r('pop_norm')} AS pop_norm FROM epts")
def _(spark, d):
    return popularity.volume_series(phases.assign(tables.real_clock(spark, d), n=30)).select(*popularity.KEYS, *r6("pop_norm"))
