"""Word vectors: continuous bag of words with negative sampling, PPMI, and Spark's own trainer.

The trainer averages models over shards: each epoch, every shard continues from the broadcast
parameters over its own sentences and returns them weighted by its words; the averages are sums
per word, so nothing but one model (vocabulary x dimension, both parameters) reaches the driver.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def ppmi(sentences: DataFrame, window: int = 5) -> DataFrame:
    """``a, b, n, ppmi``: positive pointwise mutual information of words within ``window``."""
    at = sentences.select("words", F.posexplode("words").alias("_i", "a"))
    near = F.slice("words", F.greatest(F.lit(1), F.col("_i") + 1 - window), F.least(F.col("_i") + 1, F.lit(window + 1)) + window)
    start = F.greatest(F.lit(0), F.col("_i") - window)
    pairs = at.select("_i", "a", F.posexplode(near).alias("_j", "b"), start.alias("_s")).filter(F.col("_j") + F.col("_s") != F.col("_i"))
    c = pairs.groupBy("a", "b").agg(F.count("*").alias("n"))
    m = c.groupBy("a").agg(F.sum("n").alias("m"))
    z = c.agg(F.sum("n").alias("z"))
    joined = c.join(m.select("a", F.col("m").alias("ma")), "a").join(m.select(F.col("a").alias("b"), F.col("m").alias("mb")), "b").join(F.broadcast(z), F.lit(True))
    ratio = F.col("n").cast("double") * F.col("z") / (F.col("ma") * F.col("mb"))
    return joined.filter(F.col("n") * F.col("z") > F.col("ma") * F.col("mb")).select("a", "b", "n", F.ln(ratio).alias("ppmi"))


def sgd_shard(rows: list[np.ndarray], u: np.ndarray, v: np.ndarray, noise: np.ndarray, window: int, negatives: int, rate: float, seed: int) -> int:
    """One pass over sentences of word numbers; updates ``u`` (context) and ``v`` (output)."""
    rng, seen = np.random.default_rng(seed), 0
    for words in rows:
        for i, w in enumerate(words):
            k = int(rng.integers(1, window + 1))
            ctx = np.concatenate([words[max(0, i - k) : i], words[i + 1 : i + 1 + k]])
            if not len(ctx):
                continue
            h = u[ctx].mean(axis=0)
            out = np.concatenate(([w], np.searchsorted(noise, rng.random(negatives))))
            label = np.zeros(len(out))
            label[0] = 1
            g = (label - 1 / (1 + np.exp(-np.clip(v[out] @ h, -30, 30)))) * rate
            step = g @ v[out]
            np.add.at(v, out, np.outer(g, h))
            np.add.at(u, ctx, step / len(ctx))
            seen += 1
    return seen


def train_cbow(sentences: DataFrame, dim: int = 64, window: int = 5, negatives: int = 5, epochs: int = 5, rate: float = 0.05, least: int = 2, most: int = 50_000, shards: int = 8, seed: int = 42) -> DataFrame:
    """``word, vec`` trained on ``sentences(words)``; the vocabulary is the ``most`` frequent words
    seen at least ``least`` times, which bounds what the driver and each task hold."""
    spark = sentences.sparkSession
    vocab = sentences.select(F.explode("words").alias("word")).groupBy("word").agg(F.count("*").alias("n")).filter(F.col("n") >= least).orderBy(F.desc("n"), "word").limit(most).collect()
    names = [r.word for r in vocab]
    if not names:
        return spark.createDataFrame([], "word string, vec array<float>")
    number = {w: k for k, w in enumerate(names)}
    p = np.array([r.n for r in vocab], float) ** 0.75
    noise = np.cumsum(p / p.sum())
    noise[-1] = 1.0
    rng = np.random.default_rng(seed)
    u, v = (rng.random((len(names), dim)) - 0.5) / dim, np.zeros((len(names), dim))
    dealt = sentences.select("words").repartition(shards)
    for epoch in range(epochs):
        state = spark.sparkContext.broadcast((u, v, number, noise))

        def run(batches, epoch=epoch, state=state):
            from pyspark import TaskContext

            u0, v0, ids, noise_ = state.value
            a, b, seen = u0.copy(), v0.copy(), 0
            for pdf in batches:
                rows = [np.array([ids[w] for w in ws if w in ids], np.int64) for ws in pdf["words"]]
                seen += sgd_shard(rows, a, b, noise_, window, negatives, rate * (1 - epoch / epochs), seed + 1000 * epoch + TaskContext.get().partitionId())
            changed = np.flatnonzero((a != u0).any(axis=1) | (b != v0).any(axis=1))
            yield pd.DataFrame({"k": changed, "w": float(seen), "x": [(np.concatenate([a[k] - u0[k], b[k] - v0[k]])).tolist() for k in changed]})

        parts = dealt.mapInPandas(run, "k long, w double, x array<double>")
        summed = parts.groupBy("k").agg(*[F.sum(F.col("w") * F.col("x")[j]).alias(f"c{j}") for j in range(2 * dim)], F.sum("w").alias("w")).collect()
        for r in summed:
            step = np.array(r[1 : 1 + 2 * dim]) / max(r.w, 1.0)
            u[r.k] += step[:dim]
            v[r.k] += step[dim:]
        state.unpersist()
    return spark.createDataFrame([(w, [float(x) for x in u[k]]) for k, w in enumerate(names)], "word string, vec array<float>")


def train_spark(sentences: DataFrame, dim: int = 64, window: int = 5, least: int = 2, seed: int = 42) -> DataFrame:
    """Spark's own trainer (skip-gram with hierarchical softmax), as another choice."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=least, seed=seed, inputCol="words", outputCol="v").fit(sentences)
    return model.getVectors().select("word", vector_to_array("vector", "float32").alias("vec"))


def two_corpora(event_vectors: DataFrame, general: DataFrame) -> DataFrame:
    """``event, word, vec_r, vec_d`` from vectors per event and vectors of the general corpus."""
    return event_vectors.withColumnRenamed("vec", "vec_r").join(general.withColumnRenamed("vec", "vec_d"), "word", "left")
