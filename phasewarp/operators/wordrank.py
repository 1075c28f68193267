"""Rank of words in the undirected weighted graph of a phase (damped random surfer)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phasewarp.operators.frames import plain
from phasewarp.operators.similarity import BETA, GAMMA, WordSimilarity, with_vectors
from phasewarp.sources.lineage import cut

THETA = 0.85
KEYS = ["event", "medium", "phase"]
NO_TEXT = np.zeros(0, object)


def power_iteration(a: np.ndarray, b: np.ndarray, w: np.ndarray, n: int, base: float, theta: float, tol: float, rounds: int) -> np.ndarray:
    """Scores of n vertices with edges (a, b, w); ``base`` is the count the teleport divides by."""
    strength = np.bincount(a, w, n) + np.bincount(b, w, n)
    score = np.full(n, 1.0 / n)
    for _ in range(rounds):
        flow = score / strength
        fresh = (1 - theta) / base + theta * (np.bincount(a, w * flow[b], n) + np.bincount(b, w * flow[a], n))
        moved, score = np.abs(fresh - score).max(), fresh
        if moved < tol:
            break
    return score


def rank(graph: DataFrame, theta: float = THETA, tol: float = 1e-9, rounds: int = 200, teleport: str = "phase") -> DataFrame:
    """``event, medium, phase, word, tr``; one phase graph per task, bounded by the cut-off.

    ``teleport``: divide by the phase's own words (scores sum to 1) or by those of the whole
    ``event`` (they sum to the share of words that the phase has, at the fixpoint).
    """
    ends = graph.select("event", "medium", F.col("w1").alias("w")).unionAll(graph.select("event", "medium", "w2")).distinct()
    sizes = ends.groupBy("event", "medium").agg(F.count("*").cast("double").alias("n_event"))
    joined = graph.join(F.broadcast(sizes), ["event", "medium"])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        words, at = np.unique(np.concatenate([pdf["w1"], pdf["w2"]]), return_inverse=True)
        half = len(pdf)
        base = len(words) if teleport == "phase" else pdf["n_event"].iat[0]
        tr = power_iteration(at[:half], at[half:], pdf["sim"].to_numpy(), len(words), base, theta, tol, rounds)
        return plain(pd.DataFrame({**{k: pdf[k].iat[0] for k in KEYS}, "word": words, "tr": tr}))

    return joined.groupBy(*KEYS).applyInPandas(run, "event string, medium string, phase int, word string, tr double")


def rank_series(links: DataFrame, words: DataFrame, theta: float = THETA, tol: float = 1e-9, rounds: int = 200, teleport: str = "phase") -> DataFrame:
    """The same scores from the edges of whole series and the words of their phases: one task per
    series walks its phases, so edges are never repeated per phase."""

    def run(graph: pd.DataFrame, at: pd.DataFrame) -> pd.DataFrame:
        out, all_words = [], set()
        names, ends = np.unique(np.concatenate([graph["w1"], graph["w2"]]).astype(object), return_inverse=True) if len(graph) else (np.zeros(0, object), np.zeros(0, int))
        number = {w: k for k, w in enumerate(names)}
        a, b, w = ends[: len(graph)], ends[len(graph) :], graph["sim"].to_numpy()
        phases = []
        for phase, part in at.groupby("phase"):
            here = np.zeros(len(names), bool)
            here[[number[x] for x in part["word"] if x in number]] = True
            use = here[a] & here[b]
            if use.any():
                used, local = np.unique(np.concatenate([a[use], b[use]]), return_inverse=True)
                phases.append((phase, used, local[: use.sum()], local[use.sum() :], w[use]))
                all_words.update(used.tolist())
        for phase, used, x, y, sim in phases:
            base = len(used) if teleport == "phase" else len(all_words)
            tr = power_iteration(x, y, sim, len(used), base, theta, tol, rounds)
            out.append(pd.DataFrame({"event": graph["event"].iat[0], "medium": graph["medium"].iat[0], "phase": np.int32(phase), "word": names[used], "tr": tr}))
        return plain(pd.concat(out, ignore_index=True)) if out else pd.DataFrame({"event": NO_TEXT, "medium": NO_TEXT, "phase": np.zeros(0, np.int32), "word": NO_TEXT, "tr": np.zeros(0)})

    series = ["event", "medium"]
    return (
        links.select(*series, "w1", "w2", "sim")
        .groupBy(*series)
        .cogroup(words.select(*KEYS, "word").groupBy(*series))
        .applyInPandas(run, "event string, medium string, phase int, word string, tr double")
    )


def _walk(step, start: np.ndarray, jump: np.ndarray, theta: float, tol: float, rounds: int) -> np.ndarray:
    """Scores of the phases in the columns of ``start``; a phase stops by itself."""
    score, at = start.copy(), np.arange(start.shape[1])
    for _ in range(rounds):
        fresh = jump[:, at] + theta * step(score[:, at], at)
        moved = np.abs(fresh - score[:, at]).max(axis=0)
        score[:, at] = fresh
        at = at[moved >= tol]
        if not len(at):
            break
    return score


#: Shares of the mean score: the most that clipping may add to be counted in single precision, and
#: the most that it may have changed since it was counted.
SLIGHT, EXACT = 0.1, 1e-9


def _scores(sim: WordSimilarity, strength: np.ndarray, base: np.ndarray, theta: float, tol: float, rounds: int) -> np.ndarray:
    """Scores of the words in each phase, a phase a column; ``strength`` is 0 where a word is not in
    the phase's graph.

    Where the matrix is not held, nearly all of it is linear in its factors: a round takes the
    signed product and adds what clipping at 0 gives.  That is small, and is counted anew, by a pass
    over the pairs, only while the scores still move enough to change it.  Where it is not small,
    every round passes over the pairs.
    """
    used = strength > 0
    count = np.maximum(used.sum(axis=0), 1)
    inverse = np.divide(1.0, strength, out=np.zeros(strength.shape), where=used)
    added, seen, share = np.zeros(used.shape), np.zeros(used.shape), np.full(len(count), SLIGHT)

    def product(score: np.ndarray, at: np.ndarray) -> np.ndarray:
        flow = score * inverse[:, at]
        if sim.whole is None and (share[at] <= SLIGHT).all():
            if (np.abs(score - seen[:, at]).max(axis=0) * count[at] * share[at] > EXACT).any():
                seen[:, at], added[:, at] = score, used[:, at] * sim.clipped(flow)
                share[at] = np.abs(added[:, at]).max(axis=0) * count[at]
            if (share[at] <= SLIGHT).all():
                return used[:, at] * sim.signed(flow) + added[:, at]
        return used[:, at] * sim.times(flow)

    return _walk(product, used / count, used * ((1 - theta) / base), theta, tol, rounds)


def rank_words(words: DataFrame, vectors: DataFrame, beta: float = BETA, gamma: float = GAMMA, theta: float = THETA, tol: float = 1e-9, rounds: int = 200, teleport: str = "phase", at_once: int = 32) -> DataFrame:
    """``event, medium, phase, word, tr`` from the kept words of each phase and the word vectors.

    Similarities and scores of a series are made in one task, ``at_once`` phases together, so no
    pair of words ever becomes a row; what leaves the task is linear in the words.  Memory is
    bounded by :class:`similarity.WordSimilarity` whatever the vocabulary.
    """
    series = ["event", "medium"]

    def run(told: pd.DataFrame, seen: pd.DataFrame) -> pd.DataFrame:
        told = told.sort_values("word", ignore_index=True)
        names = told["word"].to_numpy(object)
        number = {w: k for k, w in enumerate(names)}
        sim = WordSimilarity(told[["word", "vec_r", "vec_d"]], beta, gamma)
        phases = [(phase, np.sort(part["word"].map(number).to_numpy(np.int64))) for phase, part in seen.groupby("phase")]
        chunks, linked = [phases[k : k + at_once] for k in range(0, len(phases), at_once)], np.zeros(len(names), bool)
        graphs, out = [], []
        for chunk in chunks:
            member = np.zeros((len(names), len(chunk)))
            for k, (_, at) in enumerate(chunk):
                member[at, k] = 1.0
            strength = sim.strengths(member)
            for k, (phase, at) in enumerate(chunk):
                at = at[strength[at, k] > 0]
                linked[at] = True
                graphs.append((phase, at, strength[at, k]))
        for first in range(0, len(graphs), at_once):
            chunk = graphs[first : first + at_once]
            strength = np.zeros((len(names), len(chunk)))
            for k, (_, at, s) in enumerate(chunk):
                strength[at, k] = s
            # the teleport over the event divides by the words with an edge in any phase
            base = np.array([max(1, len(at) if teleport == "phase" else linked.sum()) for _, at, _ in chunk], float)
            score = _scores(sim, strength, base, theta, tol, rounds)
            out += [pd.DataFrame({"event": told["event"].iat[0], "medium": told["medium"].iat[0], "phase": np.int32(phase), "word": names[at], "tr": score[at, k]}) for k, (phase, at, _) in enumerate(chunk)]
        return plain(pd.concat(out, ignore_index=True))

    told = with_vectors(words.select(*series, "word").distinct(), vectors, series)
    told = told.select(*[F.col(c).alias(c) for c in told.columns])  # names of its own beside the other side's
    return (
        told.groupBy(*series)
        .cogroup(words.select(*KEYS, "word").groupBy(*series))
        .applyInPandas(run, "event string, medium string, phase int, word string, tr double")
    )


def rank_joined(graph: DataFrame, theta: float = THETA, tol: float = 1e-9, rounds: int = 100, teleport: str = "phase", every: int = 5) -> DataFrame:
    """The same by joins and sums for graphs beyond one task; lineage is cut every few rounds by a
    reliable checkpoint and the largest move is the only value that reaches the driver."""
    both = graph.select(*KEYS, F.col("w1").alias("i"), F.col("w2").alias("j"), "sim").unionAll(graph.select(*KEYS, "w2", "w1", "sim"))
    strength = both.groupBy(*KEYS, F.col("j")).agg(F.sum("sim").alias("s"))
    nodes = strength.select(*KEYS, F.col("j").alias("i"))
    sizes = nodes.groupBy(*KEYS).agg(F.count("*").cast("double").alias("n"))
    if teleport == "event":
        base = nodes.select("event", "medium", "i").distinct().groupBy("event", "medium").agg(F.count("*").cast("double").alias("base"))
        sizes = sizes.join(base, ["event", "medium"])
    else:
        sizes = sizes.withColumn("base", F.col("n"))
    share = cut(both.join(strength, [*KEYS, "j"]).join(sizes, KEYS).select(*KEYS, "i", "j", "base", "n", (F.col("sim") / F.col("s")).alias("p")))
    now = last = cut(share.select(*KEYS, "i", (1 / F.col("n")).alias("tr")).distinct())
    for k in range(1, rounds + 1):
        # every word has an edge, so the new scores need the old ones once
        flow = share.join(now.select(*KEYS, F.col("i").alias("j"), F.col("tr").alias("t")), [*KEYS, "j"]).groupBy(*KEYS, "i").agg(F.sum(F.col("p") * F.col("t")).alias("flow"), F.max("base").alias("base"))
        now = flow.select(*KEYS, "i", ((1 - theta) / F.col("base") + theta * F.col("flow")).alias("tr"))
        if k % every and k < rounds:
            continue
        now = cut(now)
        moved = now.join(last.withColumnRenamed("tr", "was"), [*KEYS, "i"]).agg(F.max(F.abs(F.col("tr") - F.col("was")))).first()[0]
        last = now
        if moved is None or moved < tol:
            break
    return now.select(*KEYS, F.col("i").alias("word"), "tr")
