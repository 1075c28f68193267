"""Mixing sources to target weights by systematic sampling, in DataFrame functions only.

Sources in code-point order (null last) weigh 1, 2, 3, 1, 2, 3, ... and share all words; a target
stops at ``CAP`` times its source's size and the excess goes to the others by weight.  Sorted by
the level at which a source reaches its stop, the sources that do are a prefix, so the common
level follows from running sums, without rounds.

Within a source each document expects target/size copies.  Documents are ordered by size class
and, inside a class, by an MD5 of the id; running sums of expected copies plus one random offset
per source emit a document once per integer crossed.  Ordering by size bounds the error of a
source's words by about its longest document.  The running sums come in three levels (class,
hash bucket, row), so no source, class or group of copies meets in one task.

Rows: null text has size 0; a null source is a source of its own, the last; repeated rows are
separate documents; equal order keys are interchangeable.  A source of size 0 takes nothing.
Empty tables give empty results.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phasewarp.llm.common import WORD, documents

CAP = 3
SEED = "mix-1"
BUCKET_ROWS = 1 << 16


def size_of(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def targets(sizes: DataFrame, cap: int = CAP) -> DataFrame:
    """``(source, source_size, target)`` from ``(source, source_size)``, one row per source.

    The windows here run over the list of sources, never over documents.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weighed = sizes.withColumn("w", ((F.row_number().over(by_name) - 1) % 3 + 1).cast("long"))
    by_level = Window.orderBy((F.col("stop") / F.col("w")), F.col("source").asc_nulls_last())
    all_rows = Window.partitionBy()
    ranked = (
        weighed.withColumn("stop", F.col("source_size") * F.lit(cap))
        .withColumn("total", F.sum("source_size").over(all_rows))
        .withColumn("stops_before", F.coalesce(F.sum("stop").over(by_level.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("w_from", F.sum("w").over(by_level.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("rest", F.col("total") - F.col("stops_before"))
        .withColumn("open", F.col("rest") * F.col("w") < F.col("stop") * F.col("w_from"))
        .withColumn("level", F.min(F.when(F.col("open"), F.struct((F.col("stop") / F.col("w")).alias("at"), "rest", "w_from"))).over(all_rows))
    )
    share = (F.col("level.rest") * F.col("w")).cast("double") / F.col("level.w_from")
    stopped = F.col("level").isNull() | (F.col("stop") * F.col("level.w_from") <= F.col("level.rest") * F.col("w"))
    return ranked.select("source", "source_size", F.when(stopped, F.col("stop").cast("double")).otherwise(share).alias("target"))


def _hex_number(name: str, at: int, digits: int) -> Column:
    return F.conv(F.substring(name, at, digits), 16, 10).cast("long")


def copies(docs: DataFrame, cap: int = CAP, seed: str = SEED) -> DataFrame:
    """``docs`` (with ``doc_id, source, size``) plus ``source_size, target, copies``."""
    sizes = docs.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("_n"))
    rows = sizes.agg(F.coalesce(F.sum("_n"), F.lit(0))).first()[0]
    digits = 2 + max(0, math.ceil(math.log(max(rows / BUCKET_ROWS / 256, 1), 16)))
    offset = F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n")))), 1, 8), 16, 10).cast("double") / F.lit(2.0**32)
    plan = targets(sizes.select("source", "source_size"), cap).withColumn("offset", offset)

    binary = F.bin(F.col("size") + 1)
    keyed = (
        docs.withColumn("_class", F.concat(F.lpad(F.length(binary).cast("string"), 2, "0"), F.substring(binary, 2, 4)))
        .withColumn("_h", F.md5(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("n")))))
        .withColumn("_bucket", _hex_number("_h", 1, digits))
        .withColumn("_src", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n")))
    )
    cell = keyed.groupBy("_src", "_class", "_bucket").agg(F.count("*").alias("n"))
    klass = cell.groupBy("_src", "_class").agg(F.sum("n").alias("n"))
    above = Window.partitionBy("_src").orderBy("_class").rowsBetween(Window.unboundedPreceding, -1)
    before = Window.partitionBy("_src", "_class").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = (
        cell.withColumn("_in_class", F.coalesce(F.sum("n").over(before), F.lit(0)))
        .join(klass.select("_src", "_class", F.coalesce(F.sum("n").over(above), F.lit(0)).alias("_to_class")), ["_src", "_class"])
        .select("_src", "_class", "_bucket", (F.col("_in_class") + F.col("_to_class")).alias("_start"))
    )
    inside = Window.partitionBy("_src", "_class", "_bucket").orderBy("_h", "doc_id", "size")
    placed = keyed.join(starts, ["_src", "_class", "_bucket"]).withColumn("_rank", F.col("_start") + F.row_number().over(inside))
    joined = placed.join(
        plan.select(F.coalesce(F.concat(F.lit("s"), "source"), F.lit("n")).alias("_src"), "source_size", "target", "offset"), "_src"
    )
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    crossed = F.floor(F.col("offset") + F.col("_rank") * rate) - F.floor(F.col("offset") + (F.col("_rank") - 1) * rate)
    return joined.withColumn("copies", crossed.cast("long")).select(*docs.columns, "source_size", "target", "copies")


def mix(docs: DataFrame, cap: int = CAP, seed: str = SEED) -> DataFrame:
    """The mix itself: every document as often as its copies say, columns as given."""
    columns = docs.columns
    sized = docs.withColumn("size", size_of(F.col("text")))
    return (
        copies(sized, cap, seed)
        .filter("copies > 0")
        .withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
        .select(*columns)
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "source", size_of(F.col("text")).alias("size"))
    return copies(docs).select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


SQL = f"""
WITH d AS (
  SELECT doc_id, source,
         CAST(len(list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')) AS BIGINT) AS size
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source
), w AS (
  SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS w, {CAP} * source_size AS stop FROM s
), r AS (
  SELECT *, CAST(sum(source_size) OVER () AS BIGINT)
            - CAST(coalesce(sum(stop) OVER (ORDER BY stop / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS rest,
         CAST(sum(w) OVER (ORDER BY stop / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS w_from
  FROM w
), l AS (
  SELECT rest AS l_rest, w_from AS l_w FROM r WHERE rest * w < stop * w_from ORDER BY stop / w, source NULLS LAST LIMIT 1
), t AS (
  SELECT source, source_size,
         CASE WHEN l_w IS NULL OR stop * l_w <= l_rest * w THEN CAST(stop AS DOUBLE)
              ELSE CAST(l_rest * w AS DOUBLE) / l_w END AS target,
         CAST(('0x' || substr(md5('{SEED}' || coalesce('s' || source, 'n')), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE AS shift
  FROM r LEFT JOIN l ON TRUE
), k AS (
  SELECT d.doc_id, d.size, t.source_size, t.target, t.shift,
         CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0.0::DOUBLE END AS rate,
         row_number() OVER (PARTITION BY d.source ORDER BY
             lpad(CAST(length(bin(d.size + 1)) AS VARCHAR), 2, '0') || substr(bin(d.size + 1), 2, 4),
             md5('{SEED}' || coalesce(CAST(d.doc_id AS VARCHAR), 'n')), d.doc_id, d.size) AS rn
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target,
       CAST(floor(shift + rn * rate) - floor(shift + (rn - 1) * rate) AS BIGINT) * size AS taken
FROM k
"""
