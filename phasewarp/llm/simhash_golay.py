"""SimHash near-dedup with Golay-code fuzzy keys.

A 64-bit fingerprint is cut into three segments of 22, 21 and 21 bits, each padded with zeros to
the 23 bits of the perfect binary Golay code.  Two words at most two bits apart always have a
midpoint one bit from both; the codeword nearest to it (at most three bits away) is then at most
four bits from both.  So the codewords within four bits of a segment, one or six of them, are
keys of which two such segments share at least one.

Pigeonhole over segments: with at most two differing bits in all, one of the three segments has
none.  Each key row therefore holds one exact segment and one codeword index of the segment after
it, three families in all; links are verified on the whole fingerprints.

Rows: null and empty texts have fingerprint zero and link like any others; equal fingerprints
collapse before any join.  Keys shared by more than ``HOT`` fingerprints are not paired: their
members are linked through midpoints (a fingerprint and its 64 one-bit neighbours), which is the
same relation, linear in the members.

*Similarity.*  At a Jaccard similarity of 0.8 a tenth or more of a fingerprint's bits differ, which
is beyond what keys of 64 bits can find.  :func:`similar_groups`, the pipeline's form, therefore
takes two kinds of candidates, texts whose fingerprints link as above and texts that share one of
the MinHash bands of the same shingle hashes, and verifies both by the exact Jaccard similarity of
their shingle sets.  Texts without words have one set in common.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import NO_ID, ascii_lower, components, documents, first_of_each, release, shared_folder, stored
from phasewarp.llm.passage_dedup import Candidates, batched, long_lists, signatures

HOT = 200
SHINGLE = 3
#: Members of a candidate group that are verified pair by pair; larger groups are dealt in blocks.
CROWD = 8
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Fixed value: generator polynomial of the [23, 12] Golay code, x^11+x^10+x^6+x^5+x^4+x^2+1.
GOLAY = 0b110001110101


@functools.cache
def _golay() -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """(remainder of each bit, coset leader of each remainder, per leader the codeword offsets
    that complete it to weight four)."""
    bits = []
    for k in range(23):
        r = 1 << k
        for j in range(22, 10, -1):
            if r >> j & 1:
                r ^= GOLAY << (j - 11)
        bits.append(r)
    leader = np.zeros(2048, np.int64)
    for a in range(23):
        leader[bits[a]] = 1 << a
        for b in range(a):
            leader[bits[a] ^ bits[b]] = 1 << a | 1 << b
            for c in range(b):
                leader[bits[a] ^ bits[b] ^ bits[c]] = 1 << a | 1 << b | 1 << c
    pairs: dict[int, list[int]] = {}
    for a in range(23):
        for b in range(a):
            pairs.setdefault(bits[a] ^ bits[b], []).append(1 << a | 1 << b)
    fours: list[np.ndarray] = []
    for s in range(2048):
        found = set()
        if bin(int(leader[s])).count("1") == 3:
            for p, masks in pairs.items():
                for m in masks:
                    for n in pairs.get(p ^ s, ()):
                        if not m & n:
                            found.add(m | n)
        fours.append(np.array(sorted(found), np.int64))
    return np.array(bits, np.int64), leader, fours


def _syndrome(words: np.ndarray) -> np.ndarray:
    bits = _golay()[0]
    out = np.zeros(len(words), np.int64)
    for k in range(23):
        out ^= np.where(words >> k & 1, bits[k], 0)
    return out


def codeword_keys(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, 12-bit message of a codeword within four bits) for 23-bit words: one or six each."""
    _, leader, fours = _golay()
    s = _syndrome(words)
    rows, keys = [np.arange(len(words))], [(words ^ leader[s]) >> 11]
    six = np.flatnonzero(np.array([len(fours[x]) for x in s]) == 5) if len(s) else np.zeros(0, np.int64)
    if len(six):
        near = words[six][:, None] ^ np.stack([fours[x] for x in s[six]])
        rows.append(np.repeat(six, 5))
        keys.append((near >> 11).ravel())
    return np.concatenate(rows), np.concatenate(keys)


def shingle_hashes(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """XXH64 (seed 42) of the shingles in order, repeats included; a text of fewer words is one
    shingle, a text of none has none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    k = max(1, len(words) - shingle + 1)
    line = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[:k]
    ends = ends[min(shingle, len(words)) - 1 :][:k]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(line[a:b], 42) for a, b in zip(starts.tolist(), ends.tolist())], dtype=np.uint64)


def majority(h: np.ndarray) -> int:
    """The fingerprint of shingle hashes: bits set in over half of them."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(h), 65536):
        part = h[at : at + 65536]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(ones * 2 > len(h), bitorder="little")
    return int(bits.view("<u8")[0])


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    return majority(shingle_hashes(text, shingle))


def _fingerprint_batches(shingle: int):
    def run(batches):
        for b in batches:
            prints = np.array([fingerprint(t.as_py(), shingle) for t in b.column("text")], dtype=np.uint64).view(np.int64)
            others = [n for n in b.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in others), pa.array(prints, pa.int64())], names=[*others, "fp"])
        release()

    return run


def _key_batches(batches):
    for b in batches:
        fp = b.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
        out_fp, out_key = [], []
        parts = [((fp >> np.uint64(at)) & np.uint64((1 << width) - 1)).astype(np.int64) for at, width in SEGMENTS]
        for k in range(3):
            rows, code = codeword_keys(parts[(k + 1) % 3])
            out_fp.append(fp[rows].view(np.int64))
            out_key.append((np.int64(k) << 40) | (parts[k][rows] << 12) | code)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out_key)), pa.array(np.concatenate(out_fp))], names=["key", "fp"])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """``(doc_id, fp)`` with the fingerprint as a signed 64-bit number."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(
        _fingerprint_batches(shingle), "doc_id long, fp long"
    )


def links(prints: DataFrame, folder: str, hot: int = HOT) -> DataFrame:
    """Links ``(a, b)`` whose connected components are those of "differs in at most two bits"
    over distinct fingerprints ``prints(fp)``."""
    keys = stored(prints.mapInArrow(_key_batches, "key long, fp long"), folder, "keys")
    many = keys.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    shared = stored(keys.join(many, "key"), folder, "shared-keys")
    cool = shared.filter(F.col("n") <= hot).select("key", "fp")
    other = cool.select("key", F.col("fp").alias("fp2"))
    pairs = (
        cool.join(other, "key")
        .filter((F.col("fp") < F.col("fp2")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= 2))
        .select(F.col("fp").alias("a"), F.col("fp2").alias("b"))
    )
    crowd = shared.filter(F.col("n") > hot).select("fp").distinct()
    flips = F.array(F.lit(0).cast("long"), *[F.lit(x if x < 2**63 else x - 2**64) for x in (1 << k for k in range(64))])
    around = crowd.select("fp", F.explode(F.transform(flips, lambda x: x.bitwiseXOR(F.col("fp")))).alias("mid"))
    stars = around.groupBy("mid").agg(F.min("fp").alias("b"), F.count("*").alias("n")).filter("n > 1")
    through = around.join(stars, "mid").filter(F.col("fp") != F.col("b")).select(F.col("fp").alias("a"), "b")
    return pairs.unionByName(through).distinct()


def near_groups(docs: DataFrame, hot: int = HOT, shingle: int = SHINGLE) -> DataFrame:
    """Per row ``doc_id, fingerprint, component_id`` over fingerprints linked at two or fewer bits
    (and ``fp``, ``doc_id`` kept as given)."""
    folder = shared_folder(docs.sparkSession)
    rows = stored(fingerprints(docs, shingle), folder, "fingerprints")
    distinct = stored(
        rows.groupBy("fp").agg(F.min(F.coalesce("doc_id", F.lit(NO_ID))).alias("least")), folder, "distinct"
    )
    linked = stored(links(distinct.select("fp"), folder, hot), folder, "links")
    roots = components(linked, folder)
    members = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    top = members.groupBy("root").agg(F.min("least").alias("component"))
    names = stored(members.join(top, "root").select("fp", "component"), folder, "names")
    return rows.join(names, "fp").select(
        "doc_id",
        F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"),
        F.when(F.col("component") != NO_ID, F.col("component")).alias("component_id"),
        "fp",
    )


def _sets(text: str | None, shingle: int) -> np.ndarray:
    h = shingle_hashes(text, shingle)
    return h if len(h) else np.zeros(1, np.uint64)


def _print_batches(shingle: int):
    """Rows ``(unit, text)`` to fingerprints and MinHash bands."""

    def run(batches):
        for b in batches:
            for rows in batched(b, "unit"):
                prints = np.array([fingerprint(text, shingle) for _, text in rows], np.uint64)
                sets = [_sets(text, shingle) for _, text in rows]
                sizes = np.array([len(h) for h in sets])
                with np.errstate(over="ignore"):
                    bands = signatures(np.concatenate(sets), np.cumsum(sizes) - sizes)
                yield pa.RecordBatch.from_arrays([pa.array([u for u, _ in rows], pa.int64()), pa.array(prints.view(np.int64)), long_lists(list(bands))], names=["unit", "fp", "bands"])
        release()

    return run


def _set_batches(shingle: int):
    """Rows ``(unit, text)`` to shingle sets."""

    def run(batches):
        for b in batches:
            for rows in batched(b, "unit"):
                sets = [np.unique(_sets(text, shingle)).view(np.int64) for _, text in rows]
                yield pa.RecordBatch.from_arrays([pa.array([u for u, _ in rows], pa.int64()), long_lists(sets)], names=["unit", "shingles"])
        release()

    return run


def _named(docs: DataFrame) -> DataFrame:
    """``unit`` names a text by the 64-bit hash of its lower-cased form; null counts as empty."""
    return docs.select(F.xxhash64(ascii_lower(F.col("text").cast("string"))).alias("unit"), F.col("text").cast("string").alias("text"))


def similar_groups(docs: DataFrame, shingle: int = 5, least: float = 0.8, crowd: int = CROWD) -> DataFrame:
    """``(unit, root)`` of the texts that are linked to others: components of "shingle sets have a
    Jaccard similarity of ``least`` or more" over the candidates."""
    folder = shared_folder(docs.sparkSession)
    prints = stored(_named(docs).mapInArrow(_print_batches(shingle), "unit long, fp long, bands array<long>"), folder, "prints")
    near = components(links(prints.select("fp").distinct(), f"{folder}/golay"), f"{folder}/golay")
    close = prints.select("unit", "fp").join(near, F.col("fp") == F.col("node"), "left")
    close = close.select("unit", F.array(F.xxhash64(F.lit("golay"), F.coalesce("root", "fp"))).alias("bands"))
    met = Candidates(prints.select("unit", "bands").unionAll(close), folder, crowd)
    # the copies of a text are equal once lower-cased, so any of them gives its set
    wanted = _named(docs).join(stored(met.units, folder, "units"), "unit").groupBy("unit").agg(F.min("text").alias("text"))
    sets = stored(wanted.mapInArrow(_set_batches(shingle), "unit long, shingles array<long>"), folder, "sets")
    linked = stored(met.links(sets, least), folder, "links")
    return stored(components(linked, f"{folder}/roots").select(F.col("node").alias("unit"), "root"), folder, "groups")


def keep_one(docs: DataFrame, shingle: int = 5, least: float = 0.8) -> DataFrame:
    """One row of each group of near copies stays: the one with the smallest ``doc_id`` (null is
    smallest; of several texts under it the one whose MD5 sorts first, of repeated rows the one
    whose JSON form does).  Groups are told apart by their root, since rows of several groups may
    share an id or have none.  The choice is made on narrow columns."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    keys = {"id_key": F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)), "text_key": F.md5(text)}
    rows = docs.select(*[c.alias(n) for n, c in keys.items()], F.xxhash64(ascii_lower(text)).alias("unit"))
    grouped = rows.join(similar_groups(docs, shingle, least), "unit", "left").withColumn("group", F.coalesce("root", "unit"))
    kept = grouped.groupBy("id_key", "text_key", "group").agg(F.count("*").alias("n"))
    # texts of a group under one id: the first by key stays, so a group has one (id, text)
    kept = kept.groupBy("group").agg(F.min(F.struct("id_key", "text_key", "n")).alias("top")).select("top.*")
    return first_of_each(docs.withColumns(keys).join(kept, list(keys)), list(keys), docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(documents(spark, sf_dir)).select("doc_id", "fingerprint", "component_id")
