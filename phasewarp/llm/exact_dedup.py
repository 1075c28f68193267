"""Exact dedup: static binary-fuse filters over immutable snapshots screen incoming digests.

A snapshot's distinct digests are dealt to buckets; each bucket gets one three-wise binary-fuse
filter (8-bit fingerprints), built once because a snapshot never changes.  A new batch is first
grouped by itself, then its distinct digests meet the filters bucket by bucket.  Digests that a
filter refuses are new for certain; the others join the exact bucket.  Whatever ends in a group
of two or more rows is compared byte by byte.

Rows: null text counts as empty; texts are equal when identical after lower-casing A-Z; of equal
texts the largest ``doc_id`` stays (a null ``doc_id`` is smaller than any); of rows repeated with
the same ``doc_id`` and text exactly one is kept.  Empty tables give empty results, extra columns
are ignored by :func:`decide` and passed on by :func:`keep_one`.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import NO_ID, ascii_lower, documents, first_of_each, shared_folder, shuffle_width, stored

BUCKET_KEYS = 1 << 17
FILTER_SCHEMA = "bucket long, seed long, segment long, segments long, cells binary"


def _mix(x: np.ndarray, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = x + np.uint64(seed)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))


def _places(keys: np.ndarray, seed: int, segment: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
    """Three cells, one in each of three neighbouring segments, and the fingerprint, of each key."""
    h = _mix(keys, seed)
    first = ((h >> np.uint64(32)) * np.uint64(segments)) >> np.uint64(32)
    offsets = np.stack([h & np.uint64(segment - 1), (h >> np.uint64(18)) & np.uint64(segment - 1), _mix(h, 77) & np.uint64(segment - 1)])
    cells = (first + np.arange(3, dtype=np.uint64)[:, None]) * np.uint64(segment) + offsets
    return cells.astype(np.int64), (_mix(h, 1234567) & np.uint64(255)).astype(np.uint8)


def build_filter(keys: np.ndarray) -> tuple[int, int, int, bytes]:
    """(seed, segment length, start segments, cells) of a static filter over distinct uint64 keys.

    Keys are peeled in rounds: all keys that own a cell alone leave together, and cells are then
    filled in the reverse order of leaving.  A failed peel tries the next seed.
    """
    n = len(keys)
    if n == 0:
        return 0, 4, 1, bytes(12)
    segment = 1 << max(2, min(18, int(math.floor(math.log(max(n, 2)) / math.log(3.33) + 2.25))))
    factor = max(1.125, 0.875 + 0.25 * math.log(1e6) / math.log(max(n, 2)))
    for seed in range(1, 200):
        segments = max(1, math.ceil(n * factor * (1 + 0.02 * seed) / segment) - 2)
        cells, prints = _places(keys, seed, segment, segments)
        size = (segments + 2) * segment
        count = np.bincount(cells.ravel(), minlength=size)
        total = np.zeros(size, np.int64)  # sum of key numbers in a cell: names the key once it is alone
        number = np.arange(n, dtype=np.int64)
        for row in cells:
            np.add.at(total, row, number)
        order = []
        left = n
        alone = np.flatnonzero(count == 1)
        while len(alone):
            who, at = np.unique(total[alone], return_index=True)
            order.append((who, alone[at]))
            left -= len(who)
            gone = cells[:, who]
            np.subtract.at(count, gone.ravel(), 1)
            for row in gone:
                np.subtract.at(total, row, who)
            touched = np.unique(gone)
            alone = touched[count[touched] == 1]
        if left:
            continue
        table = np.zeros(size, np.uint8)
        for who, own in reversed(order):
            table[own] = 0
            value = prints[who] ^ table[cells[0, who]] ^ table[cells[1, who]] ^ table[cells[2, who]]
            table[own] = value
        return seed, segment, segments, table.tobytes()
    raise RuntimeError("no seed peels this key set: are the keys distinct?")


def probe_filter(keys: np.ndarray, seed: int, segment: int, segments: int, cells: bytes) -> np.ndarray:
    """True where a key may be in the snapshot; never False for one that is."""
    if seed == 0:
        return np.zeros(len(keys), bool)
    at, prints = _places(keys, seed, segment, segments)
    table = np.frombuffer(cells, np.uint8)
    return (table[at[0]] ^ table[at[1]] ^ table[at[2]]) == prints


def _key_words(digests: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(d[8:16] for d in digests), dtype="<u8")


def _build_bucket(pdf: pd.DataFrame) -> pd.DataFrame:
    seed, segment, segments, cells = build_filter(np.unique(_key_words(pdf["digest"])))
    return pd.DataFrame({"bucket": [pdf["bucket"].iat[0]], "seed": [seed], "segment": [segment], "segments": [segments], "cells": [cells]})


def _probe_bucket(batch: pd.DataFrame, filters: pd.DataFrame) -> pd.DataFrame:
    hit = np.zeros(len(batch), bool)
    if len(batch):
        keys = _key_words(batch["digest"])
        for f in filters.itertuples():
            hit |= probe_filter(keys, f.seed, f.segment, f.segments, f.cells)
    return batch.assign(maybe=hit)


def digests(docs: DataFrame) -> DataFrame:
    """``(doc_id, id_key, digest, alt)``: SHA-256 and XXH64 of the normalised text."""
    text = ascii_lower(F.col("text"))
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("id_key"),
        F.unhex(F.sha2(text, 256)).alias("digest"),
        F.xxhash64(text).alias("alt"),
    )


def snapshot_filters(keys: DataFrame, buckets: int) -> DataFrame:
    """One filter row per bucket of a snapshot's distinct digests."""
    return _bucketed(keys.select("digest").distinct(), buckets).groupBy("bucket").applyInPandas(_build_bucket, FILTER_SCHEMA)


def screen(batch: DataFrame, filters: DataFrame, buckets: int) -> DataFrame:
    """Distinct batch digests with ``maybe`` (the snapshot may hold it)."""
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in batch.schema)
    return (
        _bucketed(batch, buckets)
        .groupBy("bucket")
        .cogroup(filters.groupBy("bucket"))
        .applyInPandas(_probe_bucket, f"{fields}, bucket long, maybe boolean")
        .drop("bucket")
    )


def _bucketed(df: DataFrame, buckets: int) -> DataFrame:
    return df.withColumn("bucket", F.pmod(F.xxhash64("digest"), F.lit(buckets)).cast("long"))


def _grouped(keys: DataFrame) -> DataFrame:
    return keys.groupBy("digest", "alt").agg(F.count("*").alias("n"), F.max("id_key").alias("top"))


def merge_batch(snapshot: DataFrame, batch: DataFrame, buckets: int) -> DataFrame:
    """Groups ``(digest, alt, n, top)`` over snapshot and batch keys together."""
    old, new = _grouped(snapshot), _grouped(batch)
    screened = screen(new, snapshot_filters(snapshot, buckets), buckets)
    hits = screened.filter("maybe").select("digest", "alt", F.col("n").alias("n1"), F.col("top").alias("top1"))
    met = old.join(hits, ["digest", "alt"], "full_outer").select(
        "digest", "alt",
        (F.coalesce("n", F.lit(0)) + F.coalesce("n1", F.lit(0))).alias("n"),
        F.greatest("top", "top1").alias("top"),
    )
    return met.unionByName(screened.filter("NOT maybe").drop("maybe"))


def decide(docs: DataFrame, split: int | None = None) -> DataFrame:
    """Per row ``doc_id, keep_id, group_size, kept, text_sha256`` (and ``id_key, alt, copy_no``).

    ``split``: rows up to this ``doc_id`` are the standing snapshot, later ones the new batch; by
    default the middle of the id range.
    """
    spark = docs.sparkSession
    folder = shared_folder(spark)
    keys = stored(digests(docs), folder, "digests")
    low, high, rows = keys.agg(F.min("doc_id"), F.max("doc_id"), F.count("*")).first()
    if split is None:
        split = 0 if low is None else low + (high - low) // 2
    buckets = max(shuffle_width(spark), math.ceil(rows / BUCKET_KEYS))
    old = F.coalesce(F.col("doc_id") <= split, F.lit(False))
    groups = stored(merge_batch(keys.filter(old), keys.filter(~old), buckets), folder, "groups")

    again = groups.filter("n > 1").select("digest", "alt")
    members = keys.join(again, ["digest", "alt"], "left_semi").select("id_key", "alt").distinct()
    bytes_of = (
        docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("id_key"), ascii_lower(F.col("text")).alias("text"))
        .withColumn("alt", F.xxhash64("text"))
        .join(members, ["id_key", "alt"], "left_semi")
        .withColumn("digest", F.unhex(F.sha2("text", 256)))
        .groupBy("digest", "alt")
        .agg(F.min("text").alias("lo"), F.max("text").alias("hi"))
        .select("digest", "alt", (F.col("lo") == F.col("hi")).alias("same"))
    )
    checked = stored(
        groups.join(bytes_of, ["digest", "alt"], "left").select(
            "digest", "alt", "n", "top",
            F.when((F.col("n") == 1) | F.col("same"), F.lit(True)).otherwise(F.raise_error(F.lit("two texts share SHA-256 and XXH64")).cast("boolean")).alias("same"),
        ),
        folder, "checked",
    )
    per_row = keys.groupBy("id_key", "digest", "alt").agg(F.count("*").alias("rows"))
    return (
        per_row.join(checked.filter("same"), ["digest", "alt"])
        .select("*", F.explode(F.sequence(F.lit(1), F.col("rows").cast("int"))).alias("copy_no"))
        .select(
            _id("id_key").alias("doc_id"),
            _id("top").alias("keep_id"),
            F.col("n").cast("long").alias("group_size"),
            ((F.col("id_key") == F.col("top")) & (F.col("copy_no") == 1)).alias("kept"),
            F.lower(F.hex("digest")).alias("text_sha256"),
            "id_key", "alt", "copy_no",
        )
    )


def _id(name: str):
    return F.when(F.col(name) != NO_ID, F.col(name))


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` without the rows that :func:`decide` drops; of rows repeated with one ``doc_id``
    and text, the one whose other columns sort first stays."""
    rows = decide(docs)
    kept = rows.groupBy("id_key", "alt").agg(F.count("*").alias("n"), F.max(F.col("kept").cast("int")).alias("stays")).filter("stays = 1")
    keyed = docs.withColumn("id_key", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))).withColumn("alt", F.xxhash64(ascii_lower(F.col("text"))))
    return first_of_each(keyed.join(kept, ["id_key", "alt"]), ["id_key", "alt"], docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decide(documents(spark, sf_dir)).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


SQL = """
WITH t AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS body
  FROM documents
), g AS (
  SELECT doc_id, sha256(body) AS text_sha256,
         max(doc_id) OVER (PARTITION BY body) AS keep_id,
         count(*) OVER (PARTITION BY body) AS group_size,
         row_number() OVER (PARTITION BY body, doc_id) AS copy_no
  FROM t
)
SELECT doc_id, keep_id, CAST(group_size AS BIGINT) AS group_size,
       (doc_id IS NOT DISTINCT FROM keep_id AND copy_no = 1) AS kept, text_sha256
FROM g
"""
