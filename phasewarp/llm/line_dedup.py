"""Line dedup: segment-partition edit join over distinct lines.

Two lines are linked when they are at most ``allowed(n)`` edits (of code points) apart, n the
length of the shorter: one edit for every ``CHARS_AN_EDIT`` characters and ``TAU`` at most, so
shorter lines are linked to equal ones only.  A line is cut into one segment more than it allows
edits; that many edits leave one segment whole, so each line is indexed under (length, segment
number, segment) and probes, for every length that may be linked to its own, only the substrings
whose shift is possible given the edits left on either side (multi-match-aware selection).

Keys are dealt and sorted once; runs of equal keys with two lines or more give their members as
they stream by, and only these lines' texts are fetched.  Members of a key are verified where they
meet, dealt in pairs of blocks of at most ``BLOCK`` lines, screened by letter counts (an edit moves
at most two); common ends are stripped and the rest runs the banded bit-parallel recurrence.  A
linked pair is counted under the least key that it shares, so links are counted without a row for
each pair: blocks give link counts of lines and a spanning forest.

Lines are named by the 64-bit hash of their text.  Rows: null text has no lines; an empty text has
one empty line; equal lines are one class always; repeated documents keep their own rows; extra
columns are ignored; empty tables give empty results.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import NO_ID, components, documents, release, shared_folder, shuffle_width, stored

TAU = 2
CHARS_AN_EDIT = 12
BLOCK = 512
#: Rows of one key held at most before they flow on.
HELD_ROWS = 200_000
#: Lines that a task remembers as already indexed.
SEEN_LINES = 200_000
_WORD = (1 << 64) - 1


def allowed(size: int) -> int:
    """Edits that a line of this size may be away from one that is no shorter."""
    return min(TAU, size // CHARS_AN_EDIT)


def segments(size: int, tau: int) -> list[tuple[int, int]]:
    """(start, length) of the tau + 1 segments of a line of this size; later ones are longer."""
    short, longer = divmod(size, tau + 1)
    out, at = [], 0
    for k in range(tau + 1):
        n = short + (k > tau - longer)
        out.append((at, n))
        at += n
    return out


def index_keys(line: str) -> list[int]:
    size, tau = len(line), allowed(len(line))
    return [xxhash.xxh64_intdigest(line[p : p + n], size * 16 + k) for k, (p, n) in enumerate(segments(size, tau))] if tau else []


def probe_keys(line: str) -> list[int]:
    """Keys of all lines no longer than this one that may be linked to it."""
    size, digest, out = len(line), xxhash.xxh64_intdigest, []
    for other in range(max(1, size - TAU), size + 1):
        tau, gap = allowed(other), size - other
        if not tau or gap > tau:
            continue
        for k, (p, n) in enumerate(segments(other, tau)):
            first = max(0, p - k, p + gap - (tau - k))
            last = min(size - n, p + k, p + gap + (tau - k))
            out += [digest(line[s : s + n], other * 16 + k) for s in range(first, last + 1)]
    return out


def edits_within(a: str, b: str, tau: int = TAU) -> bool:
    """Edit distance at most tau: common ends go, then a band of 2 tau + 1 diagonals is advanced
    one bit-parallel step per character (vertical deltas as two words that slide along)."""
    if abs(len(a) - len(b)) > tau:
        return False
    if a == b:
        return True
    lo, most = 0, min(len(a), len(b))
    step = 64
    while lo < most and a[lo : lo + step] == b[lo : lo + step] and lo + step <= most:
        lo += step
    while lo < most and a[lo] == b[lo]:
        lo += 1
    a, b = a[lo:], b[lo:]
    end = min(len(a), len(b))
    k = 0
    while k < end and a[-1 - k] == b[-1 - k]:
        k += 1
    if k:
        a, b = a[:-k], b[:-k]
    if not a or not b:
        return max(len(a), len(b)) <= tau
    if len(a) < len(b):
        a, b = b, a
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    up, down = _WORD << (63 - tau) & _WORD, 0  # vertical +1 and -1; bit 63 is the band's last row
    distance, at, edge = tau, tau - 63, 1 << 62
    for j, c in enumerate(b):
        bits = where.get(c, 0)
        match = (bits >> at if at >= 0 else bits << -at) & _WORD
        zero = (((match & up) + up ^ up) | match | down) & _WORD
        plus, minus = (down | ~(zero | up)) & _WORD, zero & up
        if j < len(a) - tau:
            distance += not zero >> 63
        else:
            distance += bool(plus & edge) - bool(minus & edge)
            edge >>= 1
        if distance > 2 * tau + 1:
            return False
        slid = zero >> 1
        up, down = (minus | ~(slid | plus)) & _WORD, slid & plus
        at += 1
    return distance <= tau


def _longs(names: list[str], columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=names)


def _key_batches(batches):
    """Lines ``(lid, line)`` to rows ``(key, side, lid)``, side 0 index and 1 probe; a line that this
    task has had before is passed over, within a bound."""
    seen: set[int] = set()
    for b in batches:
        keys, sides, lids = [], [], []
        for lid, line in zip(b.column("lid").to_pylist(), b.column("line")):
            if lid in seen:
                continue
            if len(seen) >= SEEN_LINES:
                seen.clear()
            seen.add(lid)
            line = line.as_py()
            index, probe = index_keys(line), probe_keys(line)
            keys += index + probe
            sides += [0] * len(index) + [1] * len(probe)
            lids += [lid] * (len(index) + len(probe))
            if len(keys) > 200_000:
                yield _longs(["key", "side", "lid"], [np.array(keys, np.uint64).view(np.int64), sides, lids])
                keys, sides, lids = [], [], []
        if keys:
            yield _longs(["key", "side", "lid"], [np.array(keys, np.uint64).view(np.int64), sides, lids])
    seen.clear()
    release()


def _live(keys: np.ndarray, sides: np.ndarray, lids: np.ndarray, known: bool = False) -> np.ndarray:
    """Distinct (key, side, lid) of whole runs of keys that hold an index row and two lines or more."""
    if not len(keys):
        return np.zeros((3, 0), np.int64)
    starts = np.concatenate(([0], np.flatnonzero(np.diff(keys)) + 1))
    good = (np.minimum.reduceat(sides, starts) == 0) & (np.minimum.reduceat(lids, starts) != np.maximum.reduceat(lids, starts)) | known
    chosen = np.repeat(good, np.diff(np.concatenate((starts, [len(keys)]))))
    rows = np.stack([keys[chosen], sides[chosen], lids[chosen]])
    order = np.lexsort(rows[::-1])
    rows = rows[:, order]
    fresh = np.ones(rows.shape[1], bool)
    fresh[1:] = (np.diff(rows, axis=1) != 0).any(axis=0)
    return rows[:, fresh]


def _live_batches(batches):
    """Rows sorted by key and side to those of live runs.  A run longer than ``HELD_ROWS`` flows on
    in parts: index rows come first, so by then it is known to be live or dead."""
    held, flowing, dead = [np.zeros(0, np.int64)] * 3, None, None
    for b in batches:
        now = [np.concatenate((h, b.column(n).to_numpy())) for h, n in zip(held, ("key", "side", "lid"))]
        if not len(now[0]):
            continue
        cut = int(np.searchsorted(now[0], now[0][-1]))  # the last run may go on
        out, done = [], [c[:cut] for c in now]
        if flowing is not None and cut and done[0][0] == flowing:
            end = int(np.searchsorted(done[0], flowing, "right"))
            out.append(_live(*(c[:end] for c in done), known=True))
            done = [c[end:] for c in done]
        if dead is not None and len(done[0]) and done[0][0] == dead:
            done = [c[int(np.searchsorted(done[0], dead, "right")) :] for c in done]
        out.append(_live(*done))
        held = [c[cut:] for c in now]
        last = int(held[0][0])
        if last == dead:
            held = [c[:0] for c in held]
        elif last == flowing or len(held[0]) > HELD_ROWS:
            if last != flowing and held[1][0] != 0:
                dead, held = last, [c[:0] for c in held]
            else:
                flowing = last
                out.append(_live(*held, known=True))
                held = [c[:0] for c in held]
        rows = np.concatenate(out, axis=1)
        if rows.shape[1]:
            yield _longs(["key", "side", "lid"], list(rows))
    rows = _live(*held)
    if rows.shape[1]:
        yield _longs(["key", "side", "lid"], list(rows))
    release()


def _counts(lines: list[str]) -> np.ndarray:
    out = np.zeros((len(lines), 32), np.int16)
    for k, line in enumerate(lines):
        for c, n in Counter(line).items():
            out[k, ord(c) & 31] += n
    return out


class _Keys:
    """Keys of lines as sets, remembered within a bound."""

    def __init__(self, make):
        self.make, self.known = make, {}

    def __call__(self, lid: int, line: str) -> set[int]:
        found = self.known.get(lid)
        if found is None:
            if len(self.known) > 20_000:
                self.known.clear()
            found = self.known[lid] = set(self.make(line))
        return found


def _block_links(key: int, index: list[tuple], probe: list[tuple], keys: tuple[_Keys, _Keys]) -> list[tuple[int, int]]:
    """Linked pairs of one block pair that are counted under this key: index lines are the shorter
    ones, of equal length those of lesser lid."""
    found = []
    screen = len(index) * len(probe) > 64
    right = _counts([x for _, x in probe]) if screen else None
    left = _counts([x for _, x in index]) if screen else None
    for k, (a, x) in enumerate(index):
        near = np.flatnonzero(np.abs(right - left[k]).sum(axis=1) <= 2 * TAU).tolist() if screen else range(len(probe))
        tau = allowed(len(x))
        for j in near:
            b, y = probe[j]
            if a == b or len(x) > len(y) or len(x) == len(y) and a > b or not edits_within(x, y, tau):
                continue
            if min(keys[0](a, x) & keys[1](b, y)) == key:
                found.append((a, b))
    return found


def _forest(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    root: dict[int, int] = {}

    def find(i: int) -> int:
        while root.setdefault(i, i) != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for a, b in pairs:
        x, y = find(a), find(b)
        if x != y:
            root[y] = x
            out.append((a, b))
    return out


def _verify_batches(batches):
    """Rows sorted by (key, p, q) to (0, a, b), edges of a forest, and (1, lid, links)."""
    keys, now, index, probe = (_Keys(index_keys), _Keys(probe_keys)), None, [], []

    def ended():
        pairs = _block_links(now[0] % (1 << 64), index, probe, keys) if index and probe else []
        n = Counter(x for pair in pairs for x in pair)
        return [(0, a, b) for a, b in _forest(pairs)] + [(1, x, c) for x, c in n.items()]

    for b in batches:
        out: list[tuple[int, int, int]] = []
        for key, p, q, side, lid, line in zip(*(b.column(n).to_pylist() for n in ("key", "p", "q", "side", "lid", "line"))):
            if (key, p, q) != now:
                out += ended() if now else []
                now, index, probe = (key, p, q), [], []
            (probe if side else index).append((lid, line))
        if out:
            yield _longs(["kind", "x", "y"], list(zip(*out)))
    if now and (out := ended()):
        yield _longs(["kind", "x", "y"], list(zip(*out)))
    release()


def live_keys(lines: DataFrame) -> DataFrame:
    """``(key, side, lid)`` of keys under which two different ``lines(lid, line)`` or more meet."""
    width = shuffle_width(lines.sparkSession)
    return (
        lines.filter(F.length("line") >= CHARS_AN_EDIT)
        .select("lid", "line")
        .mapInArrow(_key_batches, "key long, side long, lid long")
        .repartition(width, "key")
        .sortWithinPartitions("key", "side")
        .mapInArrow(_live_batches, "key long, side long, lid long")
    )


def edit_links(live: DataFrame, texts: DataFrame, folder: str) -> tuple[DataFrame, DataFrame]:
    """(forest ``(a, b)`` of the links, counts ``(lid, links)``) between ``texts(lid, line)`` that
    meet in ``live`` keys."""
    width = shuffle_width(live.sparkSession)
    sizes = live.groupBy("key").agg(F.ceil(F.count("*") / F.lit(BLOCK)).cast("int").alias("n"))
    placed = live.join(sizes, "key").withColumn("mine", F.pmod(F.xxhash64("lid"), F.col("n")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    dealt = placed.select(
        "key", "lid", "side",
        F.when(F.col("side") == 0, F.col("mine")).otherwise(F.col("other")).alias("p"),
        F.when(F.col("side") == 0, F.col("other")).otherwise(F.col("mine")).alias("q"),
    )
    found = stored(
        dealt.join(texts, "lid").repartition(width, "key", "p", "q").sortWithinPartitions("key", "p", "q").mapInArrow(_verify_batches, "kind long, x long, y long"),
        folder, "found",
    )
    edges = found.filter("kind = 0").select(F.col("x").alias("a"), F.col("y").alias("b"))
    return edges, found.filter("kind = 1").groupBy(F.col("x").alias("lid")).agg(F.sum("y").alias("links"))


def line_classes(docs: DataFrame) -> DataFrame:
    """Per line of every document ``doc_id, line_no, class_doc, class_line, links, kept``.

    The class is named by its first line in (doc_id, line_no) order, null ids first; ``links``
    counts other distinct lines within the allowed edits; ``kept`` marks the first line itself (of
    repeated documents, one copy).
    """
    folder = shared_folder(docs.sparkSession)
    base = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("id_key"), F.col("text").cast("string").alias("text"))
    lines = base.select("id_key", F.posexplode(F.split("text", "\n", -1)).alias("line_no", "line")).withColumn("lid", F.xxhash64("line"))
    rows = stored(lines.select("id_key", "line_no", "lid"), folder, "rows")
    live = stored(live_keys(lines), folder, "live")
    first = stored(rows.groupBy("lid").agg(F.min(F.struct("id_key", "line_no")).alias("first")), folder, "first")
    # the texts of lines that meet others, read at their first places
    asked = live.select("lid").distinct().join(first, "lid").groupBy(F.col("first.id_key").alias("id_key"))
    asked = asked.agg(F.collect_list(F.struct(F.col("first.line_no").alias("line_no"), "lid")).alias("wanted"))
    texts = base.join(asked, "id_key").select(F.split("text", "\n", -1).alias("lines"), F.explode("wanted").alias("w"))
    texts = texts.select(F.col("w.lid").alias("lid"), F.get("lines", F.col("w.line_no")).alias("line")).filter(F.xxhash64("line") == F.col("lid"))
    texts = stored(texts.dropDuplicates(["lid"]), folder, "texts")
    edges, counts = edit_links(live, texts, folder)
    roots = stored(components(edges, folder).select(F.col("node").alias("lid"), "root"), folder, "roots")
    named = first.join(roots, "lid").join(counts, "lid")
    tops = named.groupBy("root").agg(F.min("first").alias("top"))
    linked = named.join(tops, "root").select("lid", "top", "links")
    classes = first.join(linked, "lid", "left").select("lid", F.coalesce("top", "first").alias("top"), F.coalesce("links", F.lit(0)).alias("links"))
    placed = (
        rows.groupBy("id_key", "line_no", "lid")
        .agg(F.count("*").alias("n"))
        .join(classes, "lid")
        .select("*", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("copy_no"))
    )
    known = lambda c: F.when(c != NO_ID, c)
    return placed.select(
        known(F.col("id_key")).alias("doc_id"),
        "line_no",
        known(F.col("top.id_key")).alias("class_doc"),
        F.col("top.line_no").alias("class_line"),
        F.col("links").cast("long").alias("links"),
        ((F.col("id_key") == F.col("top.id_key")) & (F.col("line_no") == F.col("top.line_no")) & (F.col("copy_no") == 1)).alias("kept"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_classes(documents(spark, sf_dir))
