"""Functions for SQL users: Catalyst expressions under a name, and a table function for paths."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from phasewarp.operators.similarity import dot

dot_product = dot

_COUNT = "(length({w}) - length(replace({w}, c, '')))"
_CHARS = "filter(array_distinct(split({w}, '')), c -> c != '')"


def _lex_body() -> str:
    def total(x: str, y: str) -> str:
        return f"aggregate({_CHARS.format(w=x)}, 0.0D, (s, c) -> s + {_COUNT.format(w=x)} * {_COUNT.format(w=y)})"

    return f"coalesce({total('a', 'b')} / nullif(sqrt({total('a', 'a')}) * sqrt({total('b', 'b')}), 0.0D), 0.0D)"


def char_map(word: Column) -> Column:
    """Characters of a word with their counts."""
    chars = F.filter(F.array_distinct(F.split(word, "")), lambda c: c != "")
    return F.map_from_arrays(chars, F.transform(chars, lambda c: (F.length(word) - F.length(F.replace(word, c, F.lit("")))).cast("long")))


class WarpPath:
    """``warp_path(a, b, eta, tau)``: matches of two series under the level distance, with the
    temporal weight unless ``eta`` is 0."""

    def eval(self, a: list, b: list, eta: float, tau: float):
        import numpy as np

        from phasewarp.operators import warp

        x, y = np.asarray(a, float), np.asarray(b, float)
        if not len(x) or not len(y):
            return
        d = np.abs(x[:, None] - y)
        if eta:
            d = d + 1 / (1 + np.exp(np.minimum(700.0, -eta * (np.abs(np.arange(len(x))[:, None] - np.arange(len(y))) - tau))))
        g = warp.cumulate_numpy(d)
        for k, (i, j) in enumerate(warp.backtrack_numpy(g), 1):
            yield k, i, j, float(d[i - 1, j - 1]), float(g[i - 1, j - 1])


def register(spark: SparkSession) -> None:
    """``lex_sim``, ``cosine_sim``, ``temporal_weight`` and ``warp_path`` for this session."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lex_sim(a STRING, b STRING) RETURNS DOUBLE RETURN {_lex_body()}")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION cosine_sim(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN coalesce(aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, v) -> s + v)"
        " / nullif(sqrt(aggregate(a, 0.0D, (s, v) -> s + v * v)) * sqrt(aggregate(b, 0.0D, (s, v) -> s + v * v)), 0.0D), 0.0D)"
    )
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION temporal_weight(i INT, j INT, eta DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(least(700.0D, -eta * (abs(i - j) - tau))))")
    spark.udtf.register("warp_path", F.udtf(WarpPath, returnType="k int, i int, j int, d double, d_star double"))
