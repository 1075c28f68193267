"""Substring dedup: paragraph MinHash banding, with exact passages across line breaks beside it.

A text is the sequence of its words (A-Z lower-cased); places are word positions in it.  A passage
of ``LEAST`` = 50 words or more that stands at two places is a repeat; so is a paragraph (a line) of
that many words whose five-word shingles are similar to another's.  What is shorter is no passage:
documents that share a phrase or a short line only are left alone.

*Paragraphs.*  A signature is ``BANDS`` x ``ROWS`` minima over five-word shingles; at similarity 0.8
a pair shares some band with probability 1 - (1 - 0.8^3)^8, above 0.996.  Paragraphs that collide in
a band are verified by the exact Jaccard similarity of their shingle sets (0.8 or more) and
clustered by components.  Bands with more than ``CROWD`` different paragraphs are dealt in blocks;
each pair of blocks is verified whole by one product of membership matrices and gives a spanning
forest of its links only.

*Passages.*  Every window of ``ANCHOR`` words marks its least-hashed start, and the ``PIECE`` words
from it are a piece; any passage of ANCHOR + PIECE - 1 = 50 words holds one, chosen by its own words
only.  Around pieces that occur twice, every run of 50 words is hashed, and equal runs are the
repeats: in full length, also across lines, in time linear in the places.

The first place of a repeat in (doc_id, word) order stays, the others may be cut.  Documents that
share a repeat are one class.

Rows: null and empty texts have no words; null ids sort first; equal texts (64-bit hash of the
lower-cased text) are worked on once, all but the first are repeats whole if they have 50 words;
repeated rows are such copies; a row with an id of its own keeps its row whatever else repeats;
extra columns are ignored; empty tables give empty results.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import NO_ID, ascii_lower, components, documents, release, shared_folder, stored

SHINGLE = 5
SIMILAR = 0.8
LEAST = 50
PIECE = 24
ANCHOR = LEAST - PIECE + 1
BANDS, ROWS = 8, 3
CROWD = 64
BLOCK = 512
BATCH_CHARS = 1_000_000
UNITS = "key long, start int, words int, unit long, bands array<long>"
#: ``start`` of the row that tells a text's length.
WHOLE = -1
_MULTIPLY = np.random.default_rng(20240101).integers(1, 2**63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
_ADD = np.random.default_rng(20240102).integers(0, 2**63, BANDS * ROWS, dtype=np.uint64)


def _spread(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def _grams(words: np.ndarray, size: int, seed: int) -> np.ndarray:
    """Hashes of all runs of ``size`` words, from the words' own hashes."""
    n = max(len(words) - size + 1, 0)
    out = np.full(n, seed, np.uint64)
    for k in range(size):
        out = _spread(out * np.uint64(0xBF58476D1CE4E5B9) + words[k : k + n])
    return out


def anchors(grams: np.ndarray, width: int, at: np.ndarray) -> np.ndarray:
    """Positions that are the least (rightmost of equals) of the ``width`` grams from some of the
    starts ``at``, ascending."""
    if len(at) == 0:
        return np.zeros(0, np.int64)
    windows = np.lib.stride_tricks.sliding_window_view(grams, width)[at]
    return np.unique(at + width - 1 - np.argmin(windows[:, ::-1], axis=1))


def signatures(shingles: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Band keys of the shingle hashes of many paragraphs laid end to end."""
    keys = np.repeat(np.arange(BANDS, dtype=np.uint64)[None, :], len(starts), axis=0)
    for k in range(BANDS * ROWS):
        low = np.minimum.reduceat(_spread(shingles * _MULTIPLY[k] + _ADD[k]), starts)
        band = k // ROWS
        keys[:, band] = _spread(keys[:, band] * np.uint64(0x94D049BB133111EB) + low)
    return keys.view(np.int64)


class WordHashes:
    """64-bit hashes of words, remembered within a bound."""

    def __init__(self, most: int = 300_000):
        self.known: dict[bytes, int] = {}
        self.most = most

    def of(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        fresh = set(words).difference(known)
        if fresh:
            if len(known) + len(fresh) > self.most:
                known = self.known = {}
                fresh = set(words)
            digest = xxhash.xxh64_intdigest
            known.update((w, digest(w)) for w in fresh)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def text_words(text: str | None) -> tuple[list[bytes], list[tuple[int, int]]]:
    """Words of a text and (start, words) of its paragraphs."""
    words: list[bytes] = []
    paragraphs = []
    for line in (text or "").encode("utf-8", "surrogatepass").lower().split(b"\n"):
        found = line.split()
        if len(found) >= LEAST:
            paragraphs.append((len(words), len(found)))
        words += found
    return words, paragraphs


def text_units(texts: list[tuple], hashes: WordHashes) -> tuple[np.ndarray, ...]:
    """Units of ``(key, text)`` rows as columns key, start, words, unit and the band keys of the
    first rows, which are the paragraphs; then come pieces and one row per text.  Words of all
    texts are hashed and combined in one go."""
    words, sizes, paragraphs = [], [], []
    for _, text in texts:
        found, lines = text_words(text)
        paragraphs += [(len(sizes), len(words) + s, n) for s, n in lines]
        sizes.append(len(found))
        words += found
    keys, n = np.array([k for k, _ in texts], np.int64), np.array(sizes, np.int64)
    h = hashes.of(words)
    ends = np.cumsum(n)
    of = np.repeat(np.arange(len(n)), n)  # text of each word
    place = np.arange(len(h)) - (ends - n)[of]
    left = ends[of] - np.arange(len(h))
    par = np.array(paragraphs, np.int64).reshape(-1, 3)
    with np.errstate(over="ignore"):
        pieces = _grams(h, PIECE, 24)
        at = anchors(pieces, ANCHOR, np.flatnonzero(left >= LEAST))
        bands, unit = np.zeros((0, BANDS), np.int64), np.zeros(0, np.uint64)
        if len(par):
            shingles = par[:, 2] - SHINGLE + 1
            within = lambda size: np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            grams = _grams(h, SHINGLE, 5)[np.repeat(par[:, 1], shingles) + within(shingles)]
            bands = signatures(grams, np.cumsum(shingles) - shingles)
            step = within(par[:, 2])
            own = h[np.repeat(par[:, 1], par[:, 2]) + step]
            unit = np.add.reduceat(_spread(_spread(own + step.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD6E8FEB86659FD93)), np.cumsum(par[:, 2]) - par[:, 2])
            unit = _spread(unit + par[:, 2].astype(np.uint64))
    return (
        np.concatenate([keys[par[:, 0]], keys[of[at]], keys]), np.concatenate([place[par[:, 1]], place[at], np.full(len(n), WHOLE)]),
        np.concatenate([par[:, 2], np.full(len(at), PIECE), n]), np.concatenate([unit, pieces[at], np.zeros(len(n), np.uint64)]), bands,
    )


def batched(columns: pa.RecordBatch, first: str):
    """Rows of a batch in lists of bounded text."""
    rows, held = [], 0
    others = [n for n in columns.schema.names if n != first and n != "text"]
    for k, (key, text) in enumerate(zip(columns.column(first).to_pylist(), columns.column("text"))):
        rows.append((key, text.as_py(), *(columns.column(n)[k].as_py() for n in others)))
        held += len(rows[-1][1] or "")
        if held > BATCH_CHARS:
            yield rows
            rows, held = [], 0
    if rows:
        yield rows


def long_lists(parts: list[np.ndarray]) -> pa.ListArray:
    return _lists(parts, pa.int64())


def _lists(parts: list[np.ndarray], kind) -> pa.ListArray:
    offsets = np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(parts) if parts else np.zeros(0), kind))


def _unit_batches(batches):
    hashes = WordHashes()
    for b in batches:
        for rows in batched(b, "key"):
            key, start, words, unit, bands = text_units(rows, hashes)
            counts = np.concatenate([np.full(len(bands), BANDS), np.zeros(len(key) - len(bands), np.int64)])
            offsets = np.concatenate(([0], np.cumsum(counts))).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [pa.array(key), *(pa.array(c.astype(np.int32)) for c in (start, words)), pa.array(unit.view(np.int64)), pa.ListArray.from_arrays(pa.array(offsets), pa.array(bands.ravel()))],
                names=["key", "start", "words", "unit", "bands"],
            )
    del hashes
    release()


def _detail_batches(batches):
    """Per text with hits (starts of repeated pieces) and wanted paragraphs: the starts and hashes
    of all runs of ``LEAST`` words around hits, and the shingle sets."""
    hashes = WordHashes()
    for b in batches:
        for rows in batched(b, "key"):
            starts, runs, units, sets, key = [], [], [], [], []
            for k, text, hits, wanted in rows:
                h = hashes.of(text_words(text)[0])
                with np.errstate(over="ignore"):
                    grams = _grams(h, LEAST, LEAST) if hits else np.zeros(0, np.uint64)
                    hit = np.array(hits or [], np.int64)
                    at = np.unique((hit[:, None] - np.arange(ANCHOR)).ravel())
                    at = at[(at >= 0) & (at < len(grams))]
                    for w in wanted or []:
                        units.append(w["unit"])
                        sets.append(np.unique(_grams(h[w["start"] : w["start"] + w["words"]], SHINGLE, 5)).view(np.int64))
                key.append(k)
                starts.append(at.astype(np.int32))
                runs.append(grams[at].view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(key, pa.int64()), _lists(starts, pa.int32()), _lists(runs, pa.int64()), pa.nulls(len(key), pa.int64()), pa.nulls(len(key), pa.list_(pa.int64()))], names=DETAIL_NAMES)
            if units:
                none = pa.nulls(len(units), pa.int64())
                yield pa.RecordBatch.from_arrays([none, pa.nulls(len(units), pa.list_(pa.int32())), pa.nulls(len(units), pa.list_(pa.int64())), pa.array(units, pa.int64()), _lists(sets, pa.int64())], names=DETAIL_NAMES)
    del hashes
    release()


DETAIL = "key long, starts array<int>, runs array<long>, unit long, shingles array<long>"
DETAIL_NAMES = ["key", "starts", "runs", "unit", "shingles"]


def _forest(pairs: np.ndarray, n: int) -> list[tuple[int, int]]:
    root = list(range(n))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for i, j in pairs.tolist():
        x, y = find(i), find(j)
        if x != y:
            root[y] = x
            out.append((i, j))
    return out


def _block_links(least: float):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.drop_duplicates("unit").reset_index(drop=True)
        sets = [np.asarray(s) for s in pdf["shingles"]]
        values, at = np.unique(np.concatenate(sets), return_inverse=True)
        sizes = np.array([len(s) for s in sets])
        rows = np.repeat(np.arange(len(sets)), sizes)
        both = np.zeros((len(sets), len(sets)), np.float32)
        for k in range(0, len(values), 8192):
            part = (at >= k) & (at < k + 8192)
            member = np.zeros((len(sets), 8192), np.float32)
            member[rows[part], at[part] - k] = 1
            both += member @ member.T
        alike = both >= least * (sizes[:, None] + sizes[None, :] - both) - 1e-6
        found = _forest(np.argwhere(np.triu(alike, 1)), len(sets))
        units = pdf["unit"].to_numpy()
        return pd.DataFrame([(min(units[i], units[j]), max(units[i], units[j])) for i, j in found], columns=["a", "b"], dtype="int64")

    return run


class Candidates:
    """Paragraphs that share a band: pairs of them, and members of crowded bands."""

    def __init__(self, paragraphs: DataFrame, folder: str, crowd: int):
        banded = paragraphs.select("unit", F.explode("bands").alias("band")).distinct()
        sizes = banded.groupBy("band").agg(F.count("*").alias("n")).filter("n > 1")
        shared = stored(banded.join(sizes, "band"), folder, "bands")
        cool = shared.filter(F.col("n") <= crowd).select("band", "unit")
        other = cool.select("band", F.col("unit").alias("b"))
        met = cool.select("band", F.col("unit").alias("a")).join(other, "band").filter("a < b")
        self.pairs = stored(met.select("a", "b").distinct(), folder, "pairs")
        self.hot = shared.filter(F.col("n") > crowd)
        self.units = self.pairs.select(F.col("a").alias("unit")).unionAll(self.pairs.select("b")).unionAll(self.hot.select("unit")).distinct()

    def links(self, sets: DataFrame, least: float) -> DataFrame:
        """Links ``(a, b)`` between different paragraphs whose shingle sets are alike; in crowded
        bands a spanning forest of them."""
        same = F.size(F.array_intersect("x", "y"))
        verified = (
            self.pairs.join(sets.select(F.col("unit").alias("a"), F.col("shingles").alias("x")), "a")
            .join(sets.select(F.col("unit").alias("b"), F.col("shingles").alias("y")), "b")
            .filter(same >= F.lit(least) * (F.size("x") + F.size("y") - same) - 1e-9)
            .select("a", "b")
        )
        dealt = (
            self.hot.join(sets, "unit")
            .withColumn("blocks", F.ceil(F.col("n") / F.lit(BLOCK)).cast("int"))
            .withColumn("mine", F.pmod(F.xxhash64("unit"), F.col("blocks")).cast("int"))
            .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
            .select("band", "unit", "shingles", F.least("mine", "other").alias("p"), F.greatest("mine", "other").alias("q"))
        )
        crowded = dealt.groupBy("band", "p", "q").applyInPandas(_block_links(least), "a long, b long")
        return verified.unionByName(crowded).distinct()


def _at_two_places(rows: DataFrame, name: str) -> DataFrame:
    """Values of ``name`` in ``rows(name, key, start)`` that stand at two places or more."""
    ends = rows.groupBy(name).agg(F.min("key").alias("k0"), F.max("key").alias("k1"), F.min("start").alias("s0"), F.max("start").alias("s1"))
    return ends.filter("k0 <> k1 OR s0 <> s1").select(name)


def repeats(docs: DataFrame, least: float = SIMILAR, crowd: int = CROWD) -> tuple[DataFrame, DataFrame, DataFrame, str]:
    """(rows ``id_key, key``; texts ``key, first_id, n_rows, words``; places ``key, start, words,
    id0, start0`` of repeats with the first place of each; the folder they are stored in).  Texts
    are named by ``key``; ``first_id`` is the least id that has the text."""
    folder = shared_folder(docs.sparkSession)
    base = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("id_key"), F.col("text").cast("string").alias("text"))
    base = base.select("id_key", "text", F.xxhash64(ascii_lower(F.col("text"))).alias("key"))
    rows = stored(base.select("id_key", "key"), folder, "rows")
    units = stored(base.select("key", "text").mapInArrow(_unit_batches, UNITS), folder, "units")
    lengths = units.filter(F.col("start") == WHOLE).groupBy("key").agg(F.max("words").alias("words"))
    texts = stored(rows.groupBy("key").agg(F.min("id_key").alias("first_id"), F.count("*").alias("n_rows")).join(lengths, "key"), folder, "texts")

    paragraphs, pieces = units.filter(F.size("bands") > 0), units.filter((F.size("bands") == 0) & (F.col("start") != WHOLE)).select("unit", "key", "start")
    met = Candidates(paragraphs, folder, crowd)
    hits = stored(pieces.join(_at_two_places(pieces, "unit"), "unit").select("key", "start"), folder, "hits")
    wanted = paragraphs.join(met.units, "unit").groupBy("unit").agg(F.min(F.struct("key", "start", "words")).alias("at"))
    wanted = wanted.groupBy(F.col("at.key").alias("key")).agg(F.collect_list(F.struct(F.col("at.start").alias("start"), F.col("at.words").alias("words"), "unit")).alias("wanted"))
    asked = hits.groupBy("key").agg(F.collect_set("start").alias("hits")).join(wanted, "key", "full_outer").join(texts.select("key", "first_id"), "key")
    # one row of each text is read again, the one with the least id
    again = base.withColumnRenamed("id_key", "first_id").join(asked, ["key", "first_id"]).select("key", "text", "hits", "wanted")
    detail = stored(again.mapInArrow(_detail_batches, DETAIL), folder, "detail")

    links = stored(met.links(detail.filter("unit IS NOT NULL").select("unit", "shingles").dropDuplicates(["unit"]), least), folder, "links")
    roots = stored(components(links, folder).select(F.col("node").alias("unit"), "root"), folder, "roots")
    names = texts.select("key", "first_id")
    windows = detail.filter("key IS NOT NULL").select("key", F.explode(F.arrays_zip("starts", "runs")).alias("w")).select("key", F.col("w.starts").alias("start"), F.col("w.runs").alias("run"))
    windows = windows.join(names, "key")
    place = F.struct(F.col("first_id").alias("id0"), F.col("start").alias("start0"))
    first = windows.groupBy("run").agg(F.min(place).alias("f"), F.max(place).alias("l"), F.min("key").alias("k0"), F.max("key").alias("k1"))
    first = first.filter("f <> l OR k0 <> k1").select("run", "f.*")
    equal = windows.join(first, "run").select("key", "start", F.lit(LEAST).alias("words"), "id0", "start0")
    named = paragraphs.select("unit", "key", "start", "words").distinct().join(roots, "unit").join(names, "key")
    tops = named.groupBy("root").agg(F.min(place).alias("f"))
    near = named.join(tops.select("root", "f.*"), "root").select("key", "start", "words", "id0", "start0")
    return rows, texts, stored(equal.unionByName(near), folder, "places"), folder


def _merged(starts: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Overlapping and touching spans as one."""
    order = np.argsort(starts, kind="stable")
    starts, reach = starts[order], np.maximum.accumulate(stops[order])
    new = np.concatenate(([True], starts[1:] > reach[:-1])) if len(starts) else np.zeros(0, bool)
    at = np.flatnonzero(new)
    return starts[at], reach[np.concatenate((at[1:], [len(starts)])) - 1] if len(at) else reach


def _span_batches(batches):
    """Places of a text, as a list of (start, stop, later), to words covered and spans that may go."""
    for b in batches:
        covered, removed, lo, hi = [], [], [], []
        for p in b.column("places"):
            v = p.values
            start, stop, later = (v.field(k).to_numpy(zero_copy_only=False) for k in range(3))
            x, y = _merged(start, stop)
            covered.append(int((y - x).sum()))
            x, y = _merged(start[later], stop[later])
            removed.append(len(x))
            lo.append(x)
            hi.append(y)
        flat = lambda parts: pa.array(np.concatenate(parts) if parts else np.zeros(0), pa.int32())
        spans = pa.StructArray.from_arrays([flat(lo), flat(hi)], names=["start", "stop"])
        offsets = np.concatenate(([0], np.cumsum(removed))).astype(np.int32)
        yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(covered, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), spans)], names=["key", "repeated_words", "removed"])
    release()


def document_classes(docs: DataFrame, least: float = SIMILAR, crowd: int = CROWD) -> DataFrame:
    """One row per document: ``doc_id, class_id`` (smallest id reachable over shared repeats, its
    own if none), ``repeated``, ``repeated_words``, ``removed_words`` and ``removed`` (word spans
    that are not the first place of their repeat)."""
    rows, texts, places, folder = repeats(docs, least, crowd)
    known = places.join(texts.select("key", "first_id"), "key")
    edges = known.select(F.col("first_id").alias("a"), F.col("id0").alias("b")).distinct()
    roots = components(edges, f"{folder}/documents")
    later = (F.col("first_id") != F.col("id0")) | (F.col("start") != F.col("start0"))
    span = F.struct("start", (F.col("start") + F.col("words")).alias("stop"), later.alias("later"))
    spans = known.groupBy("key").agg(F.collect_list(span).alias("places")).mapInArrow(_span_batches, "key long, repeated_words long, removed array<struct<start:int,stop:int>>")
    whole = F.array(F.struct(F.lit(0).alias("start"), F.col("words").alias("stop")))
    told = texts.join(spans, "key", "left").join(roots.withColumnRenamed("node", "first_id"), "first_id", "left")
    facts = told.select(
        "key", "first_id", "words", "repeated_words", "removed",
        ((F.col("n_rows") > 1) & (F.col("words") >= LEAST)).alias("copied"), F.coalesce("root", "first_id").alias("class"), F.col("root").isNotNull().alias("linked"),
    )
    # of the rows of one text one with the first id stays
    counted = rows.groupBy("key", "id_key").agg(F.count("*").cast("int").alias("n"))
    joined = counted.join(facts, "key").withColumn("nth", F.explode(F.sequence(F.lit(1), "n")))
    copy = F.col("copied") & ((F.col("id_key") != F.col("first_id")) | (F.col("nth") > 1))
    length = F.aggregate("removed", F.lit(0), lambda s, x: s + x["stop"] - x["start"])
    id_of = lambda c: F.when(c != NO_ID, c)
    return joined.select(
        id_of(F.col("id_key")).alias("doc_id"),
        id_of(F.when(F.col("copied") | F.col("linked"), F.col("class")).otherwise(F.col("id_key"))).alias("class_id"),
        (F.col("copied") | F.col("repeated_words").isNotNull()).alias("repeated"),
        F.when(F.col("copied"), F.col("words")).otherwise(F.coalesce("repeated_words", F.lit(0))).cast("long").alias("repeated_words"),
        F.when(copy, F.col("words")).otherwise(F.coalesce(length, F.lit(0))).cast("long").alias("removed_words"),
        F.when(copy, whole).otherwise(F.coalesce("removed", F.array().cast("array<struct<start:int,stop:int>>"))).alias("removed"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return document_classes(documents(spark, sf_dir))
