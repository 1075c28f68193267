"""Toxicity with noisy-channel deobfuscation.

Words that carry digits or signs among letters, long repetitions, or letters set apart by spaces
are decoded before scoring: every character opens a few readings (itself, the letters it stands
for, nothing for separators and repetitions), and the Viterbi path through that lattice under a
trigram model of characters is the restored word, whatever its length.  A run of letters set apart
is restored whole; it is weighed as one word and by the learned words of ``LEAST_INSIDE`` letters or
more that stand in it.  The trigram counts cover all documents.

A word's weight is the largest log-odds among its learned features (the word and its prefixes).
A document's score is a logistic function of its heaviest word, the sum of weights, the number of
heavy words and of all distinct words, so a score never depends on labels, language, source or id.

Fitted on at most ``SAMPLE_ROWS`` labelled rows (those of least hash) whose crc32(doc_id) mod 4
is not 2; everything else reads all rows.  With no labels, or one class only, every score is the
share of toxic rows.  Null and empty texts get the score of a text without heavy words; repeated
rows are scored alike; extra columns are ignored by :func:`score` and kept by :func:`reject`.
"""

from __future__ import annotations

import math
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import documents, release, shared_folder, stored

THRESHOLD = 0.3
SAMPLE_ROWS = 20_000
MOST_FEATURES = 20_000
SIGNALS = 4
PREFIXES = range(4, 9)
#: Words of fewer letters are not looked for inside a run of letters set apart.
LEAST_INSIDE = 4
#: Longer words are decoded each time instead of remembered.
LONGEST_KEY = 128
#: Letters that signs stand for.
STANDS_FOR = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "l", "+": "t", "€": "e", "£": "l", "¡": "i", "(": "c"}
SEPARATORS = "._-*~'`^/\\"
DROP_COST, SIGN_COST, REPEAT_COST, KEEP_COST = 0.7, 0.7, 0.4, 3.0
EDGES = " \t\n\r\x0b\x0c.,;:?\"'()[]{}<>«»“”„!¿"
_SIGNS = re.escape("".join(STANDS_FOR) + SEPARATORS)
_ODD = re.compile(rf"[^\W\d_].*[{_SIGNS}]|[{_SIGNS}].*[^\W\d_]|([^\W\d_])\1\1")
_APART = re.compile(r"(?<!\S)[^\s](?:[ \t._*-][^\s](?=[\s._*-]|$)){2,}")
LETTERS = 28  # boundary, a-z, any other letter


def _letter(c: str) -> int:
    return ord(c) - 96 if "a" <= c <= "z" else 27 if c.isalpha() else 0


_CODES = np.array([_letter(chr(k).lower()[0]) for k in range(0x250)], np.int64)


def _trigram_batches(batches):
    total = np.zeros(LETTERS**3, np.int64)
    for b in batches:
        for t in b.column("text"):
            points = np.frombuffer((t.as_py() or "").encode("utf-32-le", "surrogatepass"), "<u4")
            for at in range(0, len(points), 1 << 20):
                part = points[max(0, at - 2) : at + (1 << 20)]
                codes = np.where(part < 0x250, _CODES[np.minimum(part, 0x24F)], 27)
                total += np.bincount((codes[:-2] * LETTERS + codes[1:-1]) * LETTERS + codes[2:], minlength=LETTERS**3) if len(codes) > 2 else 0
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["code", "n"])


def trigram_model(docs: DataFrame) -> np.ndarray:
    """log p(c | a, b) over letters from the counts of all texts; the table has a fixed size."""
    counts = np.full(LETTERS**3, 0.05)
    for r in docs.select(F.col("text").cast("string").alias("text")).mapInArrow(_trigram_batches, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect():
        counts[r.code] += r.n
    counts = counts.reshape(LETTERS, LETTERS, LETTERS)
    return np.log(counts / counts.sum(axis=2, keepdims=True)).astype(np.float32)


class Restorer:
    """Most likely reading of an obfuscated word."""

    def __init__(self, model: np.ndarray):
        self.model = model.tolist()

    def lattice(self, word: str) -> list[list[tuple[str, float]]]:
        """Per character its readings and their costs."""
        out, last = [], ""
        for c in word:
            if c.isalpha():
                options = [(c, 0.0)]
                if c == last:
                    options.append(("", REPEAT_COST))
            elif c in STANDS_FOR:
                options = [(x, SIGN_COST) for x in STANDS_FOR[c]] + [("", DROP_COST + 6.0)]
            elif c in SEPARATORS or c.isspace():
                options = [("", DROP_COST)]
            else:
                options = [("", KEEP_COST)]
            out.append(options)
            last = c
        return out

    def __call__(self, word: str) -> str:
        # a path is its last letter and the path before it: linear in the word, of any length
        paths: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
        for options in self.lattice(word):
            step: dict[tuple[int, int], tuple[float, tuple | None]] = {}
            for (a, b), (cost, path) in paths.items():
                for c, extra in options:
                    if c:
                        k = _letter(c)
                        state, total = (b, k), cost + extra - self.model[a][b][k]
                    else:
                        state, total = (a, b), cost + extra
                    if state not in step or total < step[state][0]:
                        step[state] = (total, (path, c) if c else path)
            paths = step
        ends = ((cost - self.model[a][b][0], (a, b)) for (a, b), (cost, _) in paths.items())
        path, out = paths[min(ends)[1]][1], []
        while path is not None:
            path, c = path
            out.append(c)
        return "".join(reversed(out))


class Words:
    """Words of a text as scored: lower case, edges stripped, odd ones restored (remembered)."""

    def __init__(self, model: np.ndarray, most: int = 40_000):
        self.restore, self.known, self.most = Restorer(model), {}, most

    def word(self, raw: str) -> str:
        found = self.known.get(raw)
        if found is None:
            found = raw.strip(EDGES) if not _ODD.search(raw) else self.restored(raw)
            if len(raw) <= LONGEST_KEY:
                if len(self.known) >= self.most:
                    self.known.clear()
                self.known[raw] = found
        return found

    def restored(self, raw: str) -> str:
        bare = raw.lstrip("\"'([{<«“„¿.,;:").rstrip(".,;:?\"')]}>»”")
        if not _ODD.search(bare.rstrip("!")):
            return raw.strip(EDGES)
        return self.restore(bare)

    def apart(self, text: str) -> list[str]:
        """Runs of single letters set apart, joined and restored."""
        return [self.restore(m[0]) for m in _APART.finditer(text)]

    def of(self, text: str | None) -> set[str]:
        low = (text or "").lower()
        return set(map(self.word, set(low.split()))) | set(self.apart(low))


def features(word: str) -> list[str]:
    return [f"={word}", *(word[:k] for k in PREFIXES if len(word) >= k)]


def _feature_batches(model: np.ndarray):
    def run(batches):
        words = Words(model)
        for b in batches:
            out, toxic = [], []
            for t, y in zip(b.column("text"), b.column("toxic").to_pylist()):
                found = {f for w in words.of(t.as_py()) if w for f in features(w)}
                out += found
                toxic += [y] * len(found)
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string()), pa.array(toxic, pa.int64())], names=["feature", "toxic"])
        words.known.clear()
        release()

    return run


class Scorer:
    """Document score from word weights and logistic coefficients."""

    def __init__(self, model: np.ndarray, weights: dict[str, float], line: tuple[float, ...]):
        self.model, self.weights, self.line = model, weights, line
        self.sizes = sorted({len(f) - 1 for f in weights if f[0] == "=" and len(f) > LEAST_INSIDE})
        self.words: Words | None = None
        self.known: dict[str, float] = {}

    def __getstate__(self):
        return self.model, self.weights, self.line

    def __setstate__(self, state):
        self.__init__(*state)

    def weight(self, raw: str) -> float:
        found = self.known.get(raw)
        if found is None:
            found = self._weigh(self.words.word(raw))
            if len(raw) <= LONGEST_KEY:
                if len(self.known) >= 100_000:
                    self.known.clear()
                self.known[raw] = found
        return found

    def _weigh(self, word: str) -> float:
        return max((self.weights[f] for f in features(word) if f in self.weights), default=0.0)

    def _inside(self, run: str) -> list[float]:
        """Weights in a run of letters that were set apart, where no space tells words: of the run
        as one word, and of the learned words that stand anywhere in it."""
        found = {run[at : at + n] for n in self.sizes for at in range(len(run) - n + 1) if f"={run[at : at + n]}" in self.weights}
        return [w for w in (self._weigh(run), *(self.weights[f"={x}"] for x in sorted(found) if x != run)) if w]

    def signals(self, text: str | None) -> tuple[float, ...]:
        if self.words is None:
            self.words = Words(self.model, 1_000)  # weights are remembered here, so restored words need not be
        low = (text or "").lower()
        words = set(low.split())
        heavy = [w for w in map(self.weight, words) if w]
        for run in self.words.apart(low):
            heavy += self._inside(run)
        if not heavy:
            return 0.0, 0.0, 0.0, 0.0
        return max(heavy), math.log1p(sum(heavy)), math.log1p(len(heavy)), math.log1p(len(words))

    def forget(self) -> None:
        """Drop what is remembered, at the end of a task."""
        self.words, self.known = None, {}
        release()

    def __call__(self, text: str | None) -> float:
        z = self.line[0] + sum(a * x for a, x in zip(self.line[1:], self.signals(text)))
        return 1 / (1 + math.exp(-max(-35.0, min(35.0, z))))


def _signal_batches(scorer: Scorer):
    def run(batches):
        for b in batches:
            rows = [scorer.signals(t.as_py()) for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("toxic"), *(pa.array([r[k] for r in rows], pa.float64()) for k in range(SIGNALS))], names=["toxic", *(f"x{k}" for k in range(SIGNALS))])

    return run


def _score_batches(scorer: Scorer):
    def run(batches):
        for b in batches:
            scores = [scorer(t.as_py()) for t in b.column("text")]
            at = b.schema.get_field_index("text")
            names = [n for n in b.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(c for k, c in enumerate(b.columns) if k != at), pa.array(scores, pa.float64())], names=[*names, "score"])
        scorer.forget()

    return run


def held_out(doc_id):
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, ...]:
    """Ridge logistic regression by Newton steps."""
    x = np.column_stack([np.ones(len(x)), x])
    b, ridge = np.zeros(x.shape[1]), np.diag([1e-6, *[1e-1] * (x.shape[1] - 1)])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p) + 1e-9)[:, None]) + ridge, x.T @ (y - p) - ridge @ b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in b)


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> Scorer:
    """A scorer from at most ``sample_rows`` labelled training rows of ``docs``; the broadcast
    below holds that many ids at most."""
    folder = shared_folder(docs.sparkSession)
    model = trigram_model(docs)
    chosen = (
        labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull())
        .select(F.col("doc_id").cast("long").alias("doc_id"), (F.col("toxic") > 0).cast("long").alias("toxic"))
        .filter(~held_out(F.col("doc_id")))
        .orderBy(F.xxhash64("doc_id"), "doc_id", "toxic")
        .limit(sample_rows)
    )
    sample = stored(
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id").select("text", "toxic"),
        folder, "sample",
    )
    rows, toxic = sample.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    if toxic in (0, rows):
        share = min(max(toxic / rows if rows else 0.0, 1e-6), 1 - 1e-6)
        return Scorer(model, {}, (math.log(share / (1 - share)), *[0.0] * SIGNALS))
    clean = rows - toxic
    counted = (
        sample.mapInArrow(_feature_batches(model), "feature string, toxic long")
        .groupBy("feature")
        .agg(F.sum("toxic").cast("double").alias("p"), F.sum(1 - F.col("toxic")).cast("double").alias("q"))
    )
    part = lambda k, e: F.when(k > 0, k * F.log(k / e)).otherwise(F.lit(0.0))
    n = F.col("p") + F.col("q")
    odds = F.log((F.col("p") + 0.1) / (toxic + 0.2)) - F.log((F.col("q") + 0.1) / (clean + 0.2))
    strong = (
        counted.filter("p >= 5")
        .withColumn("g", 2 * (part(F.col("p"), n * toxic / rows) + part(F.col("q"), n * clean / rows)))
        .withColumn("odds", odds)
        .filter("g > 30 AND odds > 1.5")
        .orderBy(F.desc("g"), "feature")
        .limit(MOST_FEATURES)
        .select("feature", "odds")
    )
    scorer = Scorer(model, {r.feature: float(r.odds) for r in strong.collect()}, (0.0,) * (SIGNALS + 1))
    signals = sample.mapInArrow(_signal_batches(scorer), "toxic long, " + ", ".join(f"x{k} double" for k in range(SIGNALS))).collect()
    data = np.array([tuple(r) for r in signals], float)
    return Scorer(model, scorer.weights, _logistic(data[:, 1:], data[:, 0]))


def score(docs: DataFrame, scorer: Scorer, keep: list[str]) -> DataFrame:
    """The columns ``keep`` of every row and its ``score``."""
    frame = docs.select(*keep, F.col("text").cast("string").alias("text")) if "text" not in keep else None
    if frame is None:
        raise ValueError("keep the text apart: the scorer passes it once")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema if f.name != "text")
    return frame.mapInArrow(_score_batches(scorer), f"{fields}, score double")


def _passing_batches(scorer: Scorer, threshold: float):
    def run(batches):
        for b in batches:
            yield b.filter(pa.array([scorer(t.as_py()) < threshold for t in b.column("text")], pa.bool_()))
        scorer.forget()

    return run


def reject(docs: DataFrame, scorer: Scorer, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` without the rows that score at or above the threshold, columns as given."""
    return docs.mapInArrow(_passing_batches(scorer, threshold), docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    scorer = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, scorer, ["doc_id"]).select(
        "doc_id",
        held_out(F.col("doc_id")).alias("held_out"),
        "score",
        F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).alias("predicted"),
    )


def crc_fold(doc_id: int) -> int:
    return zlib.crc32(str(doc_id).encode()) % 4
