"""Document fingerprints by consistent weighted sampling, in DataFrame functions only.

A text is a bag of words weighted by their counts.  For a word of weight w, hashes of the word
give r and c, each Gamma(2, 1), and b uniform: t = floor(ln w / r + b) and the sampling value
ln a = ln c - r (t - b + 1).  The word with the least value wins and its sample is (word, t); two
bags agree on it with probability equal to their generalised Jaccard similarity.

Each of the ``BINS`` slots has draws (r, c, b) of its own for every word and keeps the least value
over all words, so every slot is a sample of the whole bag.  A draw depends on the word alone, and a
text and its edited form share most words, so both are sampled from the same draws.

The edited text needs the next document in descending ``doc_id``.  Ids are cut at approximate
quantiles, each range is ordered by a window of its own, and a copy of each range's first row goes
to the range before it, so no window sees the whole table.  Texts are shuffled once, by range.
Counting words, sampling and picking winners then group by range and row inside the same tasks, in
generated code, and exploded words are never shuffled.

Rows: null text counts as empty; null ids come last; rows with one id are ordered by a hash of
the text, then the text; a text without words has the zero fingerprint, alike to another such; a
single row is its own next; an empty table gives an empty table; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phasewarp.llm.common import NO_ID, WORD, documents, shuffle_width

BINS = 64
#: Slots drawn side by side from one exploded row; divides BINS.
ABREAST = 4
MOST_RANGES = 4096
SPLIT = "[" + WORD[2:-2] + "]+"
_BITS = 31
#: Added to the sampling value of the empty word, which stands for no word.
_LATE = 1 << 44


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _uniform(h: Column, at: int) -> Column:
    return (F.shiftrightunsigned(h, at).bitwiseAND(F.lit((1 << _BITS) - 1)) + F.lit(0.5)) * F.lit(2.0**-_BITS)


def _packed_draw(x: Column, log_c: Column, r: Column, b: Column, t: Column, late: Column) -> Column:
    """Sampling value | 16 bits of the sample, ordered by the value; ``late`` moves it behind all others."""
    value = F.floor((log_c - r * (t - b + 1) + F.lit(512.0)) * F.lit(2.0**30)) + late
    return F.shiftleft(value, 16).bitwiseOR(F.xxhash64(x, t).bitwiseAND(F.lit(65535)))


def slot_winners(texts: DataFrame, keys: list[str], versions: int = 1) -> DataFrame:
    """``keys, best0, best1, ...``: the least draw of every slot, in slot order, over all words of
    each row's texts; ``texts(keys, v, t)`` has a row for each of its versions v = 0, 1, ...  Nulls
    for a text without words.

    Where the rows are already dealt by one of the keys nothing shuffles.  Draws are made in steps
    whose columns hold the parts that several expressions use, ``ABREAST`` slots to a row: more
    would make the generated method too long to be compiled.
    """
    col, at, every = F.col, range(ABREAST), range(versions)
    words = texts.select(*keys, "v", F.explode(F.split("t", SPLIT)).alias("w")).select(*keys, "v", F.xxhash64("w").alias("x"))
    counts = words.groupBy(*keys, "x").agg(*[F.sum((col("v") == v).cast("int")).cast("double").alias(f"n{v}") for v in every])
    late = F.when(col("x") == F.xxhash64(F.lit("")), F.lit(_LATE)).otherwise(F.lit(0).cast("long"))
    # the logarithm of 0 is null, and so is what a version draws for a word that it lacks
    held = [*keys, "x", "late", "slot", *[f"log_n{v}" for v in every]]
    rounds = F.explode(F.array(*[F.lit(k) for k in range(0, BINS, ABREAST)]))
    rows = counts.select(*keys, "x", late.alias("late"), *[F.ln(f"n{v}").alias(f"log_n{v}") for v in every]).select("*", rounds.alias("slot"))
    spread = lambda name: _uniform(col(name), 0) * _uniform(col(name), _BITS)
    rows = rows.select(*held, *[F.xxhash64("x", (col("slot") + j) * 2 + k).alias(f"{n}{j}") for j in at for k, n in ((1, "one"), (2, "two"))])
    rows = rows.select(
        *held,
        *[(-F.ln(spread(f"one{j}"))).alias(f"r{j}") for j in at],
        *[F.ln(-F.ln(spread(f"two{j}"))).alias(f"c{j}") for j in at],
        *[_uniform(col(f"one{j}").bitwiseXOR(col(f"two{j}")), 17).alias(f"b{j}") for j in at],
    )
    rows = rows.select("*", *[F.floor(col(f"log_n{v}") / col(f"r{j}") + col(f"b{j}")).alias(f"t{v}_{j}") for v in every for j in at])
    draw = lambda v, j: _packed_draw(col("x"), col(f"c{j}"), col(f"r{j}"), col(f"b{j}"), col(f"t{v}_{j}"), col("late"))
    least = rows.groupBy(*keys, "slot").agg(*[F.min(draw(v, j)).alias(f"v{v}_{j}") for v in every for j in at])
    parts = least.select(*keys, F.struct("slot", *[F.array(*[f"v{v}_{j}" for j in at]).alias(f"v{v}") for v in every]).alias("s"))
    found = parts.groupBy(*keys).agg(F.sort_array(F.collect_list("s")).alias("s"))
    known = lambda x: F.when(x < F.lit(_LATE << 16), x)
    return found.select(*keys, *[F.transform(F.flatten(F.col(f"s.v{v}")), known).alias(f"best{v}") for v in every])


def slot_signature(best: Column) -> Column:
    """``BINS`` numbers of 16 bits as an array of smallint, from the winners of all slots."""
    low = lambda v: F.coalesce(v, F.lit(0).cast("long")).bitwiseAND(F.lit(65535)).cast("int")
    return F.transform(best, lambda v: F.when(low(v) > 32767, low(v) - 65536).otherwise(low(v)).cast("smallint"))


def as_text(sig: Column) -> Column:
    return F.array_join(F.transform(sig, lambda v: F.lower(F.lpad(F.hex(v.cast("int").bitwiseAND(F.lit(65535))), 4, "0"))), "")


def likeness(a: Column, b: Column) -> Column:
    """Share of equal samples: an estimate of the generalised Jaccard similarity."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda acc, v: acc + v) / F.lit(float(BINS))


def _range_of(key: Column, bounds: list[int]) -> Column:
    """Number of bounds at or below the key, by two levels of short arrays."""
    if not bounds:
        return F.lit(0)
    step = math.isqrt(len(bounds) - 1) + 1
    parts = [bounds[k : k + step] for k in range(0, len(bounds), step)]
    heads = F.array(*[F.lit(p[0]) for p in parts])
    full = F.array(*[F.array(*[F.lit(v) for v in p]) for p in parts])
    at_or_below = lambda a: F.size(F.filter(a, lambda v: v <= key))
    return _let(at_or_below(heads), lambda i: F.when(i == 0, 0).otherwise((i - 1) * step + at_or_below(F.get(full, i - 1))))


def with_next(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Rows dealt by ranges of descending ids: ``part, rid`` (order inside the range), ``guest``
    (the copy of the next range's first row, at the end), ``doc_id, text, next_text``."""
    width = shuffle_width(docs.sparkSession)
    n = parts or min(MOST_RANGES, 16 * width)
    base = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("key"),
    )
    cuts = base.agg(F.percentile_approx("key", [k / n for k in range(1, n)], 20 * n).alias("c")).first().c if n > 1 else None
    ranged = base.withColumn("part", _range_of(F.col("key"), sorted(set(cuts or []))).cast("int"))
    tops = ranged.groupBy("part").agg(F.max("key").alias("key"))
    goes_to = F.coalesce(F.lead("part").over(Window.orderBy("part")), F.min("part").over(Window.partitionBy()))
    guests = base.join(F.broadcast(tops.select("key", goes_to.alias("part"))), "key")
    rows = ranged.withColumn("guest", F.lit(0)).unionByName(guests.withColumn("guest", F.lit(1)))
    order = Window.partitionBy("part").orderBy("guest", F.desc("key"), "h", "text")
    return (
        rows.withColumn("h", F.xxhash64("text"))
        .repartition(min(n, 4 * width), "part")
        .select("part", "guest", "doc_id", "text", F.row_number().over(order).cast("long").alias("rid"), F.lead("text").over(order).alias("next_text"))
    )


def compare(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Per row ``doc_id, n_chars, edited_sha256``, both fingerprints and both likenesses."""
    n = F.length("text")
    third = F.floor(n / 3).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), (n - third)), F.substring(F.col("next_text"), F.lit(1), third))
    rows = with_next(docs, parts).withColumn("edited", F.when(F.col("guest") == 0, edited))
    both = F.array(F.struct(F.lit(0).alias("v"), F.col("text").alias("t")), F.struct(F.lit(1).alias("v"), F.col("edited").alias("t")))
    # doc_id goes along so that both readers of the dealt rows need the same columns and share one shuffle
    texts = rows.select("part", "rid", "doc_id", F.explode(both).alias("e")).select("part", "rid", "doc_id", "e.v", "e.t").filter("t IS NOT NULL")
    order = Window.partitionBy("part").orderBy("rid")
    signed = (
        slot_winners(texts, ["part", "rid", "doc_id"], 2)
        .select("part", "rid", slot_signature(F.col("best0")).alias("sig"), slot_signature(F.col("best1")).alias("edited_sig"))
        .withColumn("next_sig", F.lead("sig").over(order))
        .filter("next_sig IS NOT NULL")  # a range's last row is a guest
        .select(
            "part", "rid",
            as_text(F.col("sig")).alias("fingerprint"),
            as_text(F.col("edited_sig")).alias("edited_fingerprint"),
            likeness(F.col("sig"), F.col("edited_sig")).alias("near_edited"),
            likeness(F.col("sig"), F.col("next_sig")).alias("near_next"),
        )
    )
    told = rows.filter("guest = 0").select("part", "rid", "doc_id", n.cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"))
    return told.join(signed, ["part", "rid"]).select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare(documents(spark, sf_dir))
