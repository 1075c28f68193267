"""Alignment of the two series of an event: ten methods, one solver.

A method is a local distance (level, slope or compound, with or without the temporal weight) and
predecessor factors.  Published settings are the defaults.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from phasewarp.operators import distances, signatures, warp
from phasewarp.sources.lineage import cut


@dataclass(frozen=True)
class Method:
    name: str
    local: str  # level, slope, compound
    eta: float | None = None
    tau: float | None = None
    bias: tuple[float, float, float] = (1.0, 1.0, 1.0)
    third: str = "cumulated"
    rule: str = "cumulated"
    factors: tuple[str, ...] = ("vocab", "level", "slope")
    order: int = 0  # complexity, for ties in ranking


BIAS = (1.2, 1.0, 1.2)
METHODS = {
    m.name: m
    for m in (
        Method("dtw", "level", order=1),
        Method("ddtw", "slope", order=2),
        Method("dtw_bias", "level", bias=BIAS, order=3),
        Method("ddtw_bias", "slope", bias=BIAS, order=3),
        Method("wdtw", "level", 10.0, 2.0, order=4),
        Method("wddtw", "slope", 5.0, 3.2, order=4),
        Method("cw", "compound", order=5),
        Method("wcw_1", "compound", 5.0, 3.2, order=6),
        Method("wcw", "compound", 10.0, 2.0, order=6),
        Method("wcw_3", "compound", 5.0, 2.2, order=6),
    )
}


def method(base: str, **changes) -> Method:
    """A published method with some of its settings changed."""
    return replace(METHODS[base], **changes)


def pack(series: DataFrame, contributive: DataFrame | None = None, s: int = 64, seed: int = 42) -> DataFrame:
    """One row per event: ``a, b`` (values), ``sa, sb`` (slopes) and, with contributive words,
    ``va, vb`` (signatures), each in phase order."""
    # twelve digits, so that equal costs are equal whatever the order their sums were made in
    s_ = distances.slopes(series.withColumn("pop_norm", F.round("pop_norm", 12))).select("event", "medium", "phase", "pop_norm", "slope")
    parts = ["pop_norm", "slope"]
    if contributive is not None:
        sigs = signatures.sign_projection(contributive, s, seed)
        s_ = s_.join(sigs, ["event", "medium", "phase"], "left").withColumn("bits", F.coalesce("bits", signatures.empty_signature(s)))
        parts.append("bits")
    # one row a series: both sides read it, and the words behind it are gone through once
    rows = cut(s_.groupBy("event", "medium").agg(F.array_sort(F.collect_list(F.struct("phase", *parts))).alias("x")))

    def column(part: str) -> Column:
        return F.transform("x", lambda e: e[part])

    def side(medium: str, names: list[str]) -> DataFrame:
        return rows.filter(F.col("medium") == medium).select("event", *[column(p).alias(n) for p, n in zip(parts, names)])

    return side("A", ["a", "sa", "va"]).join(side("B", ["b", "sb", "vb"]), "event")


def local_cost(m: Method, s: int = 64) -> Column:
    """Local costs of a packed row as ``array<array<double>>``."""

    def cell(x: Column, y: Column, i: Column, j: Column) -> Column:
        level = F.abs(x["a"] - y["b"])
        slope = F.abs(x["sa"] - y["sb"])
        if m.local == "level":
            d = level
        elif m.local == "slope":
            d = slope
        else:
            d = F.lit(1.0)
            if "vocab" in m.factors:
                d = d * signatures.distance(x["va"], y["vb"], s)
            if "level" in m.factors:
                d = d * level
            if "slope" in m.factors:
                d = d * slope
            d = F.sqrt(F.greatest(d, F.lit(0.0)))
        return d if m.eta is None else d + distances.temporal_weight(i, j, m.eta, m.tau)

    compound = m.local == "compound" and "vocab" in m.factors
    left = F.arrays_zip("a", "sa", "va") if compound else F.arrays_zip("a", "sa")
    right = F.arrays_zip("b", "sb", "vb") if compound else F.arrays_zip("b", "sb")
    return F.transform(left, lambda x, i: F.transform(right, lambda y, j: cell(x, y, i, j)))


def align(packed: DataFrame, m: Method | str = "wcw", s: int = 64, engine: str = "catalyst", band: bool = False) -> DataFrame:
    """``event, method, d, g, path`` (local costs, cumulated costs, matches) per event."""
    m = METHODS[m] if isinstance(m, str) else m
    if engine == "arrow":
        return _align_arrow(packed, m, s, band)
    costed = packed.select("event", F.lit(m.name).alias("method"), local_cost(m, s).alias("d"))
    # a hash keeps the stages apart, so that costs are computed once and not inside every step
    summed = costed.withColumn("g", warp.cumulate(F.col("d"), m.bias, m.third))
    return summed.withColumn("path", warp.backtrack(F.col("g" if m.rule == "cumulated" else "d")))


def _align_arrow(packed: DataFrame, m: Method, s: int, band: bool) -> DataFrame:
    needs_vocab = m.local == "compound" and "vocab" in m.factors
    cols = ["event", "a", "b", "sa", "sb", *(["va", "vb"] if needs_vocab else [])]

    def run(batches):
        for pdf in batches:
            out = []
            for r in pdf.itertuples():
                a, b, sa, sb = (np.asarray(x, float) for x in (r.a, r.b, r.sa, r.sb))
                level, slope = np.abs(a[:, None] - b), np.abs(sa[:, None] - sb)
                if m.local == "compound":
                    d = np.ones((len(a), len(b)))
                    if needs_vocab:
                        bits = lambda v: np.unpackbits(np.stack([np.asarray(x, np.int64) for x in v]).view(np.uint8), axis=1)
                        va, vb = bits(r.va).astype(np.int32), bits(r.vb).astype(np.int32)
                        d *= 2.0 * (va @ (1 - vb).T + (1 - va) @ vb.T) / float(s)
                    d *= level if "level" in m.factors else 1
                    d *= slope if "slope" in m.factors else 1
                    d = np.sqrt(d)
                else:
                    d = level if m.local == "level" else slope
                width = None
                if m.eta is not None:
                    omega = lambda k: 1 / (1 + np.exp(np.minimum(700.0, -m.eta * (k - m.tau))))
                    d = d + omega(np.abs(np.arange(len(a))[:, None] - np.arange(len(b))).astype(float))
                    width = warp.safe_band(d, omega) if band and m.bias == (1.0, 1.0, 1.0) else None
                g = warp.cumulate_numpy(d, m.bias, m.third, width)
                path = warp.backtrack_numpy(g if m.rule == "cumulated" else d)
                out.append((r.event, m.name, d.tolist(), g.tolist(), [{"i": i, "j": j} for i, j in path]))
            yield pd.DataFrame(out, columns=["event", "method", "d", "g", "path"])

    return packed.select(*cols).mapInPandas(run, "event string, method string, d array<array<double>>, g array<array<double>>, path array<struct<i:int,j:int>>")


def align_all(packed: DataFrame, methods: list[Method] | None = None, s: int = 64, engine: str = "catalyst") -> DataFrame:
    out = None
    for m in methods or list(METHODS.values()):
        one = align(packed, m, s, engine)
        out = one if out is None else out.unionByName(one)
    return out


def matches(aligned: DataFrame) -> DataFrame:
    """``event, method, k, i, j`` of every match."""
    return aligned.select("event", "method", F.posexplode("path").alias("_k", "_p")).select("event", "method", (F.col("_k") + 1).alias("k"), F.col("_p.i").alias("i"), F.col("_p.j").alias("j"))


def cells(aligned: DataFrame) -> DataFrame:
    """``event, method, i, j, d, d_star, on_path``: the heat map."""
    rows = aligned.select("event", "method", "path", "d", F.posexplode("g").alias("_i", "_g"))
    grid = rows.select("event", "method", "path", "_i", F.get("d", F.col("_i")).alias("_d"), F.posexplode("_g").alias("_j", "d_star"))
    here = F.struct((F.col("_i") + 1).cast("int").alias("i"), (F.col("_j") + 1).cast("int").alias("j"))
    return grid.select("event", "method", (F.col("_i") + 1).alias("i"), (F.col("_j") + 1).alias("j"), F.get("_d", F.col("_j")).alias("d"), "d_star", F.array_contains("path", here).alias("on_path"))


heatmap = cells


def links(found: DataFrame, series: DataFrame) -> DataFrame:
    """Matches with the values of both ends."""
    side = lambda medium, n, v: series.filter(F.col("medium") == medium).select("event", F.col("phase").alias(n), F.col("pop_norm").alias(v))
    return found.join(side("A", "i", "pop_a"), ["event", "i"]).join(side("B", "j", "pop_b"), ["event", "j"]).select("event", "method", "k", "i", "j", "pop_a", "pop_b")


def stripes(found: DataFrame, series: DataFrame) -> DataFrame:
    """Lead-lag stripes: position, widths, and by how much A is ahead (negative: behind)."""
    return links(found, series).withColumn("lead_a", F.col("j") - F.col("i"))


def invariants(aligned: DataFrame) -> DataFrame:
    """What every path must satisfy, per event and method."""
    from pyspark.sql import Window

    by = Window.partitionBy("event", "method").orderBy("k")
    ends = aligned.select("event", "method", F.size("g").alias("n"), F.size(F.get("g", F.lit(0))).alias("m"))
    m = matches(aligned).withColumn("di", F.col("i") - F.lag("i").over(by)).withColumn("dj", F.col("j") - F.lag("j").over(by))
    legal = F.col("di").isNull() | (F.col("di").between(0, 1) & F.col("dj").between(0, 1) & (F.col("di") + F.col("dj") > 0))
    checked = m.groupBy("event", "method").agg(
        F.min(legal).alias("twist_free"), F.count_distinct("i").alias("ci"), F.count_distinct("j").alias("cj"), F.count("*").alias("n_matches"),
        F.min(F.struct("k", "i", "j")).alias("f"), F.max(F.struct("k", "i", "j")).alias("l"),
    )
    return checked.join(ends, ["event", "method"]).select(
        "event", "method", "n_matches", "twist_free",
        ((F.col("ci") == F.col("n")) & (F.col("cj") == F.col("m"))).alias("covered"),
        ((F.col("f.i") == 1) & (F.col("f.j") == 1) & (F.col("l.i") == F.col("n")) & (F.col("l.j") == F.col("m"))).alias("ends_met"),
        F.col("n_matches").between(F.greatest("n", "m"), F.col("n") + F.col("m") - 1).alias("length_ok"),
    )
