import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from phasewarp.functions import sql as fn
from phasewarp.functions import text
from phasewarp.operators import alignment, cutoff, diagnostics, distances, frequency, grading, metrics, phases, popularity, signatures, similarity, warp, wordrank
from phasewarp.operators.alignment import METHODS

A, B = [0.1, 0.5, 0.2, 0.1, 0.1], [0.1, 0.1, 0.5, 0.2, 0.1]


def series_of(spark, a, b, event="e"):
    rows = [(event, m, k + 1, float(v)) for m, x in (("A", a), ("B", b)) for k, v in enumerate(x)]
    return spark.createDataFrame(rows, "event string, medium string, phase int, pop_norm double")


def all_paths(n, m):
    def walk(i, j):
        if (i, j) == (n, m):
            yield [(i, j)]
            return
        for di, dj in ((1, 0), (0, 1), (1, 1)):
            if i + di <= n and j + dj <= m:
                for rest in walk(i + di, j + dj):
                    yield [(i, j), *rest]

    return list(walk(1, 1))


def test_numpy_warp_is_the_minimum_over_all_paths():
    rng = np.random.default_rng(0)
    assert len(all_paths(5, 5)) == 321
    for n, m in ((1, 1), (1, 4), (3, 2), (5, 5), (4, 5)):
        d = rng.random((n, m))
        g = warp.cumulate_numpy(d)
        best = min(sum(d[i - 1, j - 1] for i, j in p) for p in all_paths(n, m))
        path = warp.backtrack_numpy(g)
        assert math.isclose(g[-1, -1], best) and math.isclose(sum(d[i - 1, j - 1] for i, j in path), best)


GOLDEN = {
    "dtw": (0.0, [(1, 1), (1, 2), (2, 3), (3, 4), (4, 5), (5, 5)], 0.9, 1.0, 0.8),
    "ddtw": (0.6, [(1, 1), (1, 2), (2, 3), (3, 4), (4, 4), (5, 5)], 0.9, 0.983333, 0.6),
    "wdtw": (0.000182, [(1, 1), (1, 2), (2, 3), (3, 4), (4, 5), (5, 5)], 0.9, 1.0, 0.8),
    "wddtw": (0.600034, [(1, 1), (2, 2), (2, 3), (3, 4), (4, 4), (5, 5)], 0.9, 0.916667, 0.4),
    "dtw_bias": (0.0, [(1, 1), (1, 2), (2, 3), (3, 4), (4, 5), (5, 5)], 0.9, 1.0, 0.8),
}


@pytest.mark.parametrize("engine", ["catalyst", "arrow"])
def test_worked_example(spark, engine):
    series = series_of(spark, A, B)
    packed = alignment.pack(series)
    aligned = alignment.align_all(packed, [METHODS[m] for m in GOLDEN], engine=engine).persist()
    stats = {r.method: r for r in metrics.path_stats(aligned).collect()}
    measured = {r.method: r for r in metrics.summary(alignment.matches(aligned), series).collect()}
    for r in aligned.collect():
        cost, path, psi_s, psi_a, lead = GOLDEN[r.method]
        assert [(p.i, p.j) for p in r.path] == path, r.method
        assert abs(stats[r.method].cost - cost) < 1e-6
        m = measured[r.method]
        assert (round(m.psi_s, 6), round(m.psi_a, 6), round(m.lead_a, 6)) == (psi_s, psi_a, lead)
        assert m.delta_b_printed == m.lead_a
    assert all(all(v for k, v in r.asDict().items() if k in ("twist_free", "covered", "ends_met", "length_ok")) for r in alignment.invariants(aligned).collect())


def test_compound_methods_and_vocabulary(spark):
    series = series_of(spark, A, B)
    words = [("e", m, k, w) for m, shift in (("A", 0), ("B", 1)) for k in range(1, 6) for w in (f"w{k - shift}", "all", f"x{k - shift}")]
    contrib = spark.createDataFrame(words, "event string, medium string, phase int, word string")
    packed = alignment.pack(series, contrib)
    for name in ("cw", "wcw", "wcw_1", "wcw_3"):
        one = alignment.align(packed, name).first()
        two = alignment.align(packed, name, engine="arrow").first()
        assert np.allclose(one.g, two.g) and one.path == two.path
    assert abs(alignment.align(packed, "cw").first().g[-1][-1]) < 1e-9


def test_engines_and_band_agree_on_random_series(spark):
    rng = np.random.default_rng(3)
    rows = []
    for e in range(4):
        for m in "AB":
            x = rng.random(40)
            rows += [(str(e), m, k + 1, float(v)) for k, v in enumerate(x / x.sum())]
    packed = alignment.pack(spark.createDataFrame(rows, "event string, medium string, phase int, pop_norm double"))
    for name in ("dtw", "dtw_bias", "wdtw", "wddtw"):
        one = {r.event: (r.g, r.path) for r in alignment.align(packed, name).collect()}
        for r in alignment.align(packed, name, engine="arrow").collect():
            assert np.allclose(r.g, one[r.event][0]) and r.path == one[r.event][1]
        for r in alignment.align(packed, name, engine="arrow", band=True).collect():
            assert math.isclose(r.g[-1][-1], one[r.event][0][-1][-1])
            assert r.path == one[r.event][1]


def test_unit_bias_is_plain_and_swapping_media_keeps_cost(spark):
    ab, ba = alignment.pack(series_of(spark, A, B)), alignment.pack(series_of(spark, B, A))
    for name in METHODS:
        if METHODS[name].local == "compound":
            continue
        x, y = alignment.align(ab, name).first(), alignment.align(ba, name).first()
        assert math.isclose(x.g[-1][-1], y.g[-1][-1], abs_tol=1e-12)
    plain = alignment.align(ab, alignment.method("dtw", bias=(1.0, 1.0, 1.0))).first()
    assert plain.g == alignment.align(ab, "dtw").first().g


def test_rank_on_the_star(spark):
    graph = spark.createDataFrame([("e", "A", 1, "a", "b", 0.5), ("e", "A", 1, "a", "c", 0.25)], "event string, medium string, phase int, w1 string, w2 string, sim double")
    want = {"a": 0.486486, "b": 0.325676, "c": 0.187838}
    words = spark.createDataFrame([("e", "A", 1, w) for w in "abcz"], "event string, medium string, phase int, word string")
    for got in (wordrank.rank(graph, tol=1e-12, rounds=400), wordrank.rank_series(graph, words, tol=1e-12, rounds=400)):
        assert {r.word: round(r.tr, 6) for r in got.collect()} == want
    joined = {r.word: r.tr for r in wordrank.rank_joined(graph, rounds=30, every=10).collect()}
    assert all(abs(joined[w] - {"a": 0.485318, "b": 0.326455, "c": 0.188227}[w]) < 1e-6 for w in joined) and len(joined) == 3
    thirty = {r.word: round(r.tr, 6) for r in wordrank.rank(graph, tol=0, rounds=30).collect()}
    assert thirty == {"a": 0.485318, "b": 0.326455, "c": 0.188227}


def test_rank_solves_the_linear_system(spark):
    rng = np.random.default_rng(5)
    names = [f"w{k:02d}" for k in range(12)]
    pairs = [(a, b, float(rng.random())) for a, b in itertools.combinations(names, 2) if rng.random() < 0.5]
    graph = spark.createDataFrame([("e", "A", 1, *p) for p in pairs], "event string, medium string, phase int, w1 string, w2 string, sim double")
    used = sorted({x for p in pairs for x in p[:2]})
    m = np.zeros((len(used), len(used)))
    for a, b, v in pairs:
        m[used.index(a), used.index(b)] = m[used.index(b), used.index(a)] = v
    exact = np.linalg.solve(np.eye(len(used)) - 0.85 * m / m.sum(axis=0), np.full(len(used), 0.15 / len(used)))
    got = {r.word: r.tr for r in wordrank.rank(graph, tol=1e-14, rounds=1000).collect()}
    assert np.allclose([got[w] for w in used], exact) and math.isclose(sum(got.values()), 1.0)


def test_exact_power_law(spark):
    vocab = spark.createDataFrame([("e", "A", f"w{r:02d}", 1000.0 * r**-2) for r in range(1, 51)], "event string, medium string, word string, freq double")
    scope = ["event", "medium"]
    ranks = cutoff.ranked(vocab, scope)
    fit = cutoff.threshold(cutoff.median_rank(cutoff.fit_power_law(ranks, scope)))
    r = fit.first()
    assert (round(r.alpha, 9), round(r.h, 5), round(r.r_half, 9), round(r.th, 6)) == (2, 1000, 2, 250) and r.regime == "infinite"
    assert {x.word for x in cutoff.kept_words(ranks, fit, scope).collect()} == {"w01", "w02"}
    flat = cutoff.median_rank(cutoff.fit_power_law(cutoff.ranked(vocab.withColumn("freq", F.sqrt("freq")), scope), scope)).first()
    assert flat.regime == "truncated" and abs(flat.r_half - math.sqrt(50)) < 1e-6


def test_lexical_similarity(spark):
    fn.register(spark)
    one = spark.sql("SELECT 'night' a, 'nacht' b").select(similarity.lexical(F.col("a"), F.col("b")).alias("x"), F.expr("lex_sim(a, b)").alias("y"), similarity.lexical(F.col("a"), F.col("a")).alias("s"), similarity.lexical(F.col("a"), F.lit("")).alias("z")).first()
    assert round(one.x, 9) == round(one.y, 9) == 0.6 and round(one.s, 9) == 1 and one.z == 0
    path = spark.sql("SELECT t.* FROM VALUES (1) v(x), LATERAL warp_path(array(.1D,.5D,.2D,.1D,.1D), array(.1D,.1D,.5D,.2D,.1D), 0D, 0D) t ORDER BY k").collect()
    assert [(r.i, r.j) for r in path] == GOLDEN["dtw"][1]


def test_temporal_weight(spark):
    want = {(10.0, 2.0): [0, 4.5e-5, 0.5, 0.999955, 1], (5.0, 3.2): [0, 1.7e-5, 0.002473, 0.268941, 0.982014], (5.0, 2.2): [1.7e-5, 0.002473, 0.268941, 0.982014, 0.999877]}
    for (eta, tau), values in want.items():
        got = [r.w for r in spark.range(5).select(F.round(distances.temporal_weight(F.col("id"), F.lit(0), eta, tau), 6).alias("w")).collect()]
        assert np.allclose(got, values, atol=1e-6)


def test_signature_estimates_the_angle(spark):
    a, b = [f"w{k}" for k in range(20)], [f"w{k}" for k in range(8, 28)]
    words = spark.createDataFrame([("e", "A", 1, w) for w in a] + [("e", "B", 1, w) for w in b] + [("e", "B", 2, w) for w in a], "event string, medium string, phase int, word string")
    got = []
    for seed in range(6):
        sig = {(r.medium, r.phase): r.bits for r in signatures.sign_projection(words, 256, seed).collect()}
        hamming = sum(bin(x ^ y).count("1") for x, y in zip(sig["A", 1], sig["B", 1]))
        got.append(2 * hamming / 256)
        assert sig["A", 1] == sig["B", 2]
    want = 2 * math.acos(12 / 20) / math.pi
    assert abs(np.mean(got) - want) < 0.1
    assert sum(bin(v).count("1") for v in spark.range(1).select(signatures.empty_signature(100).alias("b")).first().b) == 100


def test_normalise_dense_and_edge_cases(spark):
    raw = spark.createDataFrame([("e", "A", 1, 2.0), ("e", "A", 3, 6.0), ("e", "B", 2, 0.0)], "event string, medium string, phase int, pop double")
    got = {(r.medium, r.phase): r.pop_norm for r in popularity.normalise(phases.densify(raw, 4)).collect()}
    assert len(got) == 8 and got["A", 1] == 0.25 and got["A", 3] == 0.75 and got["B", 2] == 0
    for x in ([0.7], [0.4, 0.6]):
        one = distances.slopes(series_of(spark, x, x)).collect()
        assert all(r.slope == 0 for r in one)
        assert [(p.i, p.j) for p in alignment.align(alignment.pack(series_of(spark, x, x)), "dtw").first().path] == [(k + 1, k + 1) for k in range(len(x))]
    with pytest.raises(Exception, match="unequal spans"):
        metrics.require_same_span(series_of(spark, A, B[:4])).collect()


def test_semantic_weight_end_to_end(spark):
    rows = []
    for phase in (1, 2, 3):
        for m in "AB":
            rows += [("e", m, phase, w, f, f) for w, f in (("storm", 9 * phase), ("storms", 4), ("rain", 5), ("zzz", 1))]
    rows.append(("e", "A", 4, "zzz", 1, 1))
    words = spark.createDataFrame(rows, "event string, medium string, phase int, word string, freq long, rec_freq long")
    vec = spark.createDataFrame([("e", w, v, v) for w, v in (("storm", [1.0, 0.1]), ("storms", [1.0, 0.2]), ("rain", [0.8, 0.5]), ("zzz", [-1.0, 0.0]))], "event string, word string, vec_r array<float>, vec_d array<float>")
    for strategy in ("series", "grouped"):
        swp = popularity.semantic_weight(words, vec, popularity.SwpConfig(n_phases=4, th=3.0), strategy)
        got = {(r.medium, r.phase): r.pop_norm for r in swp.series.collect()}
        assert len(got) == 8 and got["A", 4] == 0
        assert math.isclose(sum(v for (m, _), v in got.items() if m == "A"), 1) and got["A", 3] > got["A", 1]
        assert "zzz" not in {r.word for r in swp.contributive.collect()}
    stream = popularity.word_stream(swp.word_pop, 2).collect()
    assert all(math.isclose(r.y1 - r.y0, r["pop"]) and r.share <= 1 for r in stream)
    counts = popularity.semantic_weight(words, vec, popularity.SwpConfig(n_phases=4, th=3.0, compensation="count", total="all", teleport="event")).series
    assert counts.count() == 8


def test_diagnostics_and_grades(spark):
    m = spark.createDataFrame([("e", "dtw", k, 1, k) for k in range(1, 6)] + [("e", "wcw", k, k, k) for k in range(1, 6)], "event string, method string, k int, i int, j int")
    d = {r.method: (r.n_singular, r.n_far) for r in diagnostics.defects(m).collect()}
    assert d == {"dtw": (1, 2), "wcw": (0, 0)}
    g = {r.method: r.grade for r in grading.rank_methods(m, diagnostics.defects(m)).collect()}
    assert g == {"wcw": 1, "dtw": 2}
    s = series_of(spark, A, B)
    assert {(r.medium, r.phase) for r in diagnostics.peaks(s).collect()} == {("A", 2), ("B", 1), ("B", 3)}
    assert {(r.medium, r.phase) for r in diagnostics.burst_alert(s, 1, 3).collect()} == {("A", 2), ("B", 3)}


def test_text_functions(spark):
    t = spark.createDataFrame([("en", "The STORM, see https://x.y/z <b>now</b> 2024!"), ("en", None), ("de", "Der Sturm und die Flut")], "lang string, text string")
    got = [r.words for r in text.prepare(t).select("words").collect()]
    assert "storm" in got[0] and "the" not in got[0] and got[1] is None and got[2] == ["sturm", "flut"]
    assert t.select(text.format_text(F.col("text")).alias("x")).first().x == "the storm see b now b 2024"
    seg = lambda m, x, **k: spark.createDataFrame([(x,)], "t string").select(text.segment(F.col("t"), m, **k).alias("w")).first().w
    assert seg("char_bigram", "abc d") == ["ab", "bc", "cd"] and seg("char_bigram", "") == []
    assert seg("dict_maxmatch", "stormwater!", dictionary=["storm", "water"], longest=5) == ["storm", "water"]
    p = text.prepare(spark.createDataFrame([("en", "New York storm 42")], "lang string, text string"), phrases=["new york"], keep_numbers=False).first().words
    assert p == ["new_york", "storm"]


def test_counts_are_additive_over_resolutions(spark):
    rec = spark.createDataFrame([("e", "A", 1, ["a", "a", "b"]), ("e", "A", 2, ["a"]), ("e", "A", 3, ["b"])], "event string, medium string, phase int, words array<string>")
    w = frequency.phase_words(rec)
    assert {(r.phase, r.word): (r.freq, r.rec_freq) for r in w.collect()}[1, "a"] == (2, 1)
    assert {(r.phase, r.word): r.freq for r in frequency.coarser(w, 2).collect()} == {(1, "a"): 3, (1, "b"): 1, (2, "b"): 1}


def test_front_has_one_shuffle_and_no_python(spark, sf):
    from phasewarp.plans.queries import p1

    plan = frequency.phase_words(p1(spark, sf, clock="hash"))._jdf.queryExecution().toString()
    executed = plan[plan.index("== Physical Plan ==") :]
    assert executed.count("Exchange hashpartitioning") == 1 and "Python" not in executed and "Cartesian" not in executed
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in executed
