"""Similarity between words: vectors of two corpora and characters."""

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from phasewarp.operators.frames import plain

BETA, GAMMA = 0.7, 0.02


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two vectors; 0 where one is missing or zero."""
    return F.coalesce(dot(a, b) / F.nullif(F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)), F.lit(0.0)), F.lit(0.0))


def char_counts(word: Column) -> Column:
    """Distinct characters of a word with their counts."""
    chars = F.filter(F.array_distinct(F.split(word, "")), lambda c: c != "")
    return F.transform(chars, lambda c: F.struct(c.alias("c"), (F.length(word) - F.length(F.replace(word, c, F.lit("")))).cast("double").alias("n")))


def _norm(counts: Column) -> Column:
    return F.sqrt(F.aggregate(counts, F.lit(0.0), lambda s, e: s + e["n"] * e["n"]))


def _shared(counts: Column, word: Column) -> Column:
    return F.aggregate(counts, F.lit(0.0), lambda s, e: s + e["n"] * (F.length(word) - F.length(F.replace(word, e["c"], F.lit("")))).cast("double"))


def lexical(a: Column, b: Column) -> Column:
    """Cosine of two words' character counts."""
    ca, cb = char_counts(a), char_counts(b)
    return F.coalesce(_shared(ca, b) / F.nullif(_norm(ca) * _norm(cb), F.lit(0.0)), F.lit(0.0))


def combine(semantic: Column, lexical_part: Column, gamma: float = GAMMA) -> Column:
    return F.lit(gamma) * semantic + F.lit(1 - gamma) * lexical_part


def rank_numbers(vocab: DataFrame, embeddings: DataFrame) -> DataFrame:
    """``event, word, number`` of its vectors: r-1 for the event's word of frequency rank r, counted
    round the table."""
    n = embeddings.agg(F.nullif(F.count("*"), F.lit(0)).alias("n"))
    by = Window.partitionBy("event").orderBy(F.desc("freq"), "word")
    words = vocab.groupBy("event", "word").agg(F.sum("freq").alias("freq")).withColumn("r", F.row_number().over(by)).join(F.broadcast(n), F.lit(True))
    return words.select("event", "word", ((F.col("r") - 1) % F.col("n")).alias("number"))


def numbered_vectors(embeddings: DataFrame, shift: int = 37) -> DataFrame:
    """``number, vec_r, vec_d``: the table's vector of that number and the one ``shift`` further on."""
    n = embeddings.agg(F.nullif(F.count("*"), F.lit(0)).alias("n"))
    vec_r = embeddings.select(F.col("vec_id").alias("number"), F.col("embedding").alias("vec_r"))
    inside = embeddings.join(F.broadcast(n), (F.col("vec_id") >= 0) & (F.col("vec_id") < F.col("n")))
    vec_d = inside.select(F.pmod(F.col("vec_id") - shift, F.col("n")).alias("number"), F.col("embedding").alias("vec_d"))
    return vec_r.join(vec_d, "number", "full")


def rank_vectors(vocab: DataFrame, embeddings: DataFrame, shift: int = 37) -> DataFrame:
    """Stand-in vectors: in each event the word of frequency rank r takes the vectors number r-1
    (event corpus) and r-1+shift (general corpus), counted round the table."""
    return rank_numbers(vocab, embeddings).join(numbered_vectors(embeddings, shift), "number", "left").select("event", "word", "vec_r", "vec_d")


def _unit_rows(vectors: pd.Series) -> np.ndarray:
    """Vectors scaled to length one as rows; missing or zero ones as zeros."""
    size = max((len(v) for v in vectors if v is not None), default=1)
    m = np.zeros((len(vectors), size))
    for k, v in enumerate(vectors):
        if v is not None:
            m[k] = v
    norm = np.linalg.norm(m, axis=1, keepdims=True)
    return m / np.where(norm == 0, 1, norm)


def _character_rows(words: pd.Series) -> np.ndarray:
    chars = {c: k for k, c in enumerate(sorted(set("".join(words))))}
    m = np.zeros((len(words), max(1, len(chars))))
    for k, w in enumerate(words):
        for c in w:
            m[k, chars[c]] += 1
    return m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)


def with_vectors(kept: DataFrame, vectors: DataFrame, scope: list[str]) -> DataFrame:
    return kept.select(*scope, "word").join(vectors, [c for c in ("event", "word") if c in vectors.columns], "left")


class WordSimilarity:
    """Positive similarities between the words of one series, as products with vectors: the whole
    matrix is held up to ``HELD_WORDS`` words, beyond that its tiles are made anew from the
    factors, so memory stays linear in the words and no word is left out."""

    HELD_WORDS = 4096
    TILE = 1024

    def __init__(self, pdf: pd.DataFrame, beta: float = BETA, gamma: float = GAMMA):
        parts = [_unit_rows(pdf["vec_r"]), _unit_rows(pdf["vec_d"]), _character_rows(pdf["word"])]
        self.x = np.hstack(parts)
        weight = np.repeat([gamma * beta, gamma * (1 - beta), 1 - gamma], [p.shape[1] for p in parts])
        self.y = self.x * weight
        self.own = (self.y * self.x).sum(axis=1, keepdims=True)
        self.whole = None
        if len(pdf) <= self.HELD_WORDS:
            self.whole = self._tile(slice(None), slice(None), True)
        self.codes = _character_codes(parts[2], abs(gamma) * (abs(beta) + abs(1 - beta)), 1 - gamma)
        self.order = np.argsort(self.codes, kind="stable")

    def _tile(self, i: slice, j: slice, diagonal: bool) -> np.ndarray:
        sim = self.y[i] @ self.x[j].T
        if diagonal:
            np.fill_diagonal(sim, 0.0)
        return np.maximum(sim, 0.0, out=sim)

    def times(self, f: np.ndarray) -> np.ndarray:
        """The matrix times the columns of ``f``; each pair of words is computed once."""
        if self.whole is not None:
            return self.whole @ f
        out = np.zeros(f.shape)
        for i, j in tiles(len(f), self.TILE):
            sim = self._tile(i, j, i == j)
            out[i] += sim @ f[j]
            if i != j:
                out[j] += sim.T @ f[i]
        return out

    def signed(self, f: np.ndarray) -> np.ndarray:
        """``times`` with negative similarities left in, which takes time linear in the words."""
        return self.y @ (self.x.T @ f) - self.own * f

    def strengths(self, member: np.ndarray) -> np.ndarray:
        """``times`` where ``member`` (zeros and ones) is set: the signed product and what clipping
        adds.  Sums so small that rounding may have made them are counted as ``times`` does."""
        if self.whole is not None:
            return (self.whole @ member) * member
        out = (self.signed(member) + self.clipped(member, np.float64)) * member
        low = np.flatnonzero(((out <= 1e-6 * out.max(initial=0.0)) & (member > 0)).any(axis=1))
        if 2 * len(low) > len(out):
            return self.times(member) * member
        for a in range(0, len(low), self.TILE):
            i = low[a : a + self.TILE]
            out[i] = 0.0
            for b in range(0, len(out), self.TILE):
                sim = self._tile(i, slice(b, b + self.TILE), False)
                at = np.flatnonzero((i >= b) & (i < b + self.TILE))
                sim[at, i[at] - b] = 0.0
                out[i] += (sim @ member[b : b + self.TILE]) * member[i]
        return out

    def clipped(self, f: np.ndarray, kind: type = np.float32) -> np.ndarray:
        """What ``times`` has beyond ``signed``, in single precision or as told, from the pairs of
        ``apart``."""
        x, y, g, out = (m[self.order].astype(kind) for m in (self.x, self.y, f, np.zeros(f.shape)))
        for i, j, same in self.apart():
            sim = y[i] @ x[j].T
            if same:
                np.fill_diagonal(sim, 0.0)
            np.minimum(sim, 0.0, out=sim)
            out[i] -= sim @ g[j]
            if not same:
                out[j] -= sim.T @ g[i]
        back = np.empty_like(out)
        back[self.order] = out
        return back

    def apart(self) -> Iterator[tuple[slice, slice | np.ndarray, bool]]:
        """Blocks of places in ``order`` (rows, columns, are they the same) that hold every pair
        whose similarity can be negative, once."""
        codes, starts = np.unique(self.codes[self.order], return_index=True)
        ends = [*starts[1:], len(self.order)]
        for k, code in enumerate(codes):
            blocks = [slice(a, min(a + self.TILE, ends[k])) for a in range(starts[k], ends[k], self.TILE)]
            others = [np.arange(starts[m], ends[m]) for m in range(k + 1, len(codes)) if not codes[m] & code]
            others = np.concatenate(others) if others else np.zeros(0, np.int64)
            for n, i in enumerate(blocks):
                if not code:
                    yield from ((i, j, i == j) for j in blocks[n:])
                yield from ((i, others[a : a + self.TILE], False) for a in range(0, len(others), self.TILE))


def _character_codes(c: np.ndarray, reach: float, weight: float) -> np.ndarray:
    """A bit for each of the most common characters that a word has.  Two words with a bit in common
    have a lexical part, times ``weight``, of ``reach`` at least, which no semantic part undoes.  Words
    so long or repetitive that this is not certain get no bits."""
    has = c > 0
    common = np.argsort(-has.sum(axis=0), kind="stable")[: min(10, int(np.log2(max(1, len(c) / 64))))]
    least = np.where(has, c, np.inf).min(axis=1)
    sure = weight * least**2 > 1.001 * reach
    return np.where(sure, has[:, common] @ (1 << np.arange(len(common))), 0).astype(np.int64)


def tiles(n: int, size: int):
    """Slices (rows, columns) of the upper half of an n x n matrix."""
    cuts = [slice(k, min(k + size, n)) for k in range(0, n, size)]
    for k, i in enumerate(cuts):
        for j in cuts[k:]:
            yield i, j


class _Cosines:
    """Products of rows of length one; 0 where a vector is missing, also beside one that is not finite."""

    def __init__(self, rows: np.ndarray, known: np.ndarray):
        self.rows, self.known, self.finite = rows, known, bool(np.isfinite(rows).all())

    def tile(self, i: slice, j: slice) -> np.ndarray:
        out = self.rows[i] @ self.rows[j].T
        if not self.finite:
            out[~self.known[i]] = 0.0
            out[:, ~self.known[j]] = 0.0
        return out


def _mixed(parts: list[tuple[float, np.ndarray | None]]) -> np.ndarray:
    """Weighted sum of the parts that are there."""
    first, *more = [p if w == 1 else w * p for w, p in parts if p is not None]
    return sum(more, first)


def _totals(words: DataFrame, scope: list[str], mixes: list[tuple[float, float]], beta: float, tile: int) -> DataFrame:
    """``pair_totals`` of rows that stand for one word each or, with a column ``n_words``, for so
    many words of equal vectors."""
    kinds = {"mix": "int32", "n_pairs": "int64", "n_positive": "int64", "total": "float64", "top": "float64"}
    counted, characters = "n_words" in words.columns, any(q for _, q in mixes)
    semantic = any(p for p, _ in mixes) or not characters

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(batches), ignore_index=True)
        r, d = (_Cosines(_unit_rows(pdf[c]), pdf[c].notna().to_numpy()) for c in ("vec_r", "vec_d"))
        c = _character_rows(pdf["word"]) if characters else None
        # what has no weight is multiplied only where it is not finite
        use_r, use_d = ((semantic and w != 0) or not x.finite for x, w in ((r, beta), (d, 1 - beta)))
        n = pdf["n_words"].to_numpy(np.float64) if counted else np.ones(len(pdf))
        found = [[0, 0, 0.0, -np.inf] for _ in mixes]
        for i, j in tiles(len(pdf), tile):
            sem = _mixed([(beta, r.tile(i, j) if use_r else None), (1 - beta, d.tile(i, j) if use_d else None)]) if use_r or use_d else None
            lex = c[i] @ c[j].T if characters else None
            pairs = np.triu(np.outer(n[i], n[j]), 1) + np.diag(n[i] * (n[i] - 1) / 2) if i == j else None
            for x, (p, q) in zip(found, mixes):
                v = _mixed([(p, sem), (q, lex)])
                if i == j:
                    v, count = v[pairs > 0], pairs[pairs > 0]
                    if not v.size:
                        continue
                    sums = count.sum(), count[~(v <= 0)].sum(), count @ v
                else:
                    positive = ~(v <= 0)
                    sums = n[i].sum() * n[j].sum(), n[i] @ positive @ n[j] if counted else np.count_nonzero(positive), n[i] @ v @ n[j]
                # NaN counts as the greatest number, as in SQL
                x[:] = x[0] + int(sums[0]), x[1] + int(sums[1]), x[2] + float(sums[2]), float(np.maximum(x[3], v.max()))
        rows = [(k, *x) for k, x in enumerate(found) if x[0]]
        if rows:
            yield plain(pd.DataFrame({**{k: pdf[k].iat[0] for k in scope}, **{k: [x[n] for x in rows] for n, k in enumerate(kinds)}}).astype(kinds))

    fields = ", ".join(f"{k} string" for k in scope)
    out = words.groupBy(*scope).applyInPandas(run, f"{fields}, mix int, n_pairs long, n_positive long, total double, top double")
    return out.withColumns({k: F.coalesce(k, F.lit(float("nan"))) for k in ("total", "top")})  # pandas takes NaN for null


def pair_totals(kept: DataFrame, vectors: DataFrame, scope: list[str], mixes: list[tuple[float, float]], beta: float = BETA, tile: int = 1024) -> DataFrame:
    """``scope, mix, n_pairs, n_positive, total, top`` over every pair of words of a series, where
    mix number k is a x semantic + b x lexical for ``mixes[k] = (a, b)``.  Pairs are summed where
    they are made, a tile at a time, and never become rows."""
    return _totals(with_vectors(kept, vectors, scope), scope, mixes, beta, tile)


def semantic_totals(kept: DataFrame, numbers: DataFrame, vectors: DataFrame, scope: list[str], beta: float = BETA, tile: int = 1024) -> DataFrame:
    """``pair_totals`` of the semantic part alone, from ``rank_numbers`` and ``numbered_vectors``:
    words of one number have equal vectors, so each number of a series is one row with its count of
    words, and a series is no larger than the table of vectors however many words it has."""
    counts = kept.select(*scope, "word").join(numbers, ["event", "word"], "left").groupBy(*scope, "number").agg(F.count("*").alias("n_words"))
    return _totals(counts.join(vectors, "number", "left"), scope, [(1.0, 0.0)], beta, tile)


def edges(kept: DataFrame, vectors: DataFrame, scope: list[str], beta: float = BETA, gamma: float = GAMMA, only_positive: bool = True) -> DataFrame:
    """``scope, w1, w2, sem, str, sim`` with w1 < w2, once per series, after the cut-off only.

    The pairs of a series are three matrix products in one task, which leave it a block of rows at
    a time, about ``at_once`` pairs.
    """
    words, at_once = with_vectors(kept, vectors, scope), 1 << 19

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(batches)).sort_values("word", ignore_index=True)
        r, d, c = _unit_rows(pdf["vec_r"]), _unit_rows(pdf["vec_d"]), _character_rows(pdf["word"])
        names = pdf["word"].to_numpy(object)
        rows = max(1, at_once // len(pdf))
        for at in range(0, len(pdf), rows):
            block = slice(at, min(at + rows, len(pdf)))
            sem, lex = beta * (r[block] @ r.T) + (1 - beta) * (d[block] @ d.T), c[block] @ c.T
            sim = gamma * sem + (1 - gamma) * lex
            later = np.arange(block.start, block.stop)[:, None] < np.arange(len(pdf))
            i, j = np.nonzero(later & (sim > 0) if only_positive else later)
            if len(i):
                yield plain(pd.DataFrame({**{k: pdf[k].iat[0] for k in scope}, "w1": names[at + i], "w2": names[j], "sem": sem[i, j], "str": lex[i, j], "sim": sim[i, j]}))

    fields = ", ".join(f"{k} string" for k in scope)
    return words.groupBy(*scope).applyInPandas(run, f"{fields}, w1 string, w2 string, sem double, str double, sim double")


def phase_edges(links: DataFrame, words: DataFrame) -> DataFrame:
    """The positive edges of each phase: both ends occur in it."""
    at = words.select("event", "medium", "phase", "word")
    return links.join(at.withColumnRenamed("word", "w1"), ["event", "medium", "w1"]).join(at.withColumnRenamed("word", "w2"), ["event", "medium", "phase", "w2"]).select("event", "medium", "phase", "w1", "w2", "sim")


def contributive(graph: DataFrame) -> DataFrame:
    """Words with an edge in their phase."""
    keys = ["event", "medium", "phase"]
    return graph.select(*keys, F.col("w1").alias("word")).unionAll(graph.select(*keys, "w2")).distinct()
