"""Series of more words than the similarity matrix is held for."""

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from phasewarp.operators import alignment, frequency, popularity, signatures, similarity, wordrank
from phasewarp.plans import queries

SCHEMA = "event string, medium string, phase int, word string, freq long"


def drawn(n=60, phases=3):
    rng = np.random.default_rng(5)
    words = sorted({"".join(rng.choice(list("abcdefghijklmnop"), rng.integers(2, 7))) for _ in range(n)}) + ["zz", "éê"]
    rows = [("e", m, int(p), w, int(rng.integers(1, 9))) for m in "AB" for p in range(1, phases + 1) for w in words if rng.random() < 0.7]
    vectors = [("e", w, rng.normal(size=8).tolist(), rng.normal(size=8).tolist()) for w in words[:-2]]
    return rows, vectors


def frames(spark):
    rows, vectors = drawn()
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(vectors, "event string, word string, vec_r array<double>, vec_d array<double>")


def told():
    _, vectors = drawn()
    return pd.DataFrame([v[1:] for v in vectors], columns=["word", "vec_r", "vec_d"])


def test_tiles_give_the_products_of_the_whole_matrix(monkeypatch):
    held = similarity.WordSimilarity(told())
    monkeypatch.setattr(similarity.WordSimilarity, "HELD_WORDS", 0)
    monkeypatch.setattr(similarity.WordSimilarity, "TILE", 7)
    made = similarity.WordSimilarity(told())
    f = np.random.default_rng(1).random((len(held.whole), 4))
    assert made.whole is None
    assert np.allclose(made.times(f), held.whole @ f, rtol=1e-13)
    assert np.allclose(made.signed(f) + made.clipped(f), held.whole @ f, rtol=1e-6)


@pytest.mark.parametrize("gamma", [similarity.GAMMA, 0.9])
def test_scores_without_the_matrix_take_few_passes_and_equal_those_with_it(monkeypatch, gamma):
    passes = []

    def scores():
        sim = similarity.WordSimilarity(told(), gamma=gamma)
        member = (np.random.default_rng(2).random((len(sim.x), 3)) < 0.8).astype(float)
        strength = sim.times(member) * member
        for name in ("times", "clipped"):
            monkeypatch.setattr(sim, name, lambda f, go=getattr(sim, name): (passes.append(1), go(f))[1])
        return wordrank._scores(sim, strength, np.maximum((strength > 0).sum(axis=0), 1), 0.85, 0.0, 40)

    want = scores()
    passes.clear()
    monkeypatch.setattr(similarity.WordSimilarity, "HELD_WORDS", 0)
    assert np.abs(scores() - want).max() < 1e-9
    assert len(passes) < 20 or gamma > 0.5  # 40 rounds


@pytest.mark.parametrize("teleport", ["phase", "event"])
def test_ranks_in_the_task_equal_ranks_of_edges(spark, teleport):
    words, vectors = frames(spark)
    links = similarity.edges(words.select("event", "medium", "word").distinct(), vectors, ["event", "medium"])
    want = {r[:4]: r.tr for r in wordrank.rank_series(links, words, tol=0.0, rounds=30, teleport=teleport).collect()}
    for at_once in (2, 32):
        got = {r[:4]: r.tr for r in wordrank.rank_words(words, vectors, tol=0.0, rounds=30, teleport=teleport, at_once=at_once).collect()}
        assert got.keys() == want.keys() and max(abs(got[k] - want[k]) for k in want) < 1e-12


def test_teleport_over_the_event_makes_no_pair_rows(spark, monkeypatch):
    words, vectors = frames(spark)
    real = similarity.edges
    monkeypatch.setattr(similarity, "edges", lambda *a, **k: real(*a, **k).filter("raise_error('pairs were made') IS NULL"))
    assert popularity.semantic_weight(words, vectors, popularity.SwpConfig(th=1.0, teleport="event")).ranks.count() > 0


def test_pair_totals_equal_sums_over_the_pairs(spark):
    words, vectors = frames(spark)
    kept = words.select("event", "medium", "word").distinct().unionAll(spark.createDataFrame([("e", "C", "zz")], "event string, medium string, word string"))
    scope, g = ["event", "medium"], similarity.GAMMA
    pairs = similarity.edges(kept, vectors, scope, only_positive=False)
    mixes = [(1.0, 0.0), (0.0, 1.0), (g, 1 - g)]
    got = similarity.pair_totals(kept, vectors, scope, mixes, tile=9)
    for k, c in enumerate(("sem", "str", "sim")):
        want = pairs.groupBy(*scope).agg(F.count("*"), F.count(F.when(F.col(c) > 0, 1)), F.sum(c), F.max(c)).collect()
        found = {(r.event, r.medium): r for r in got.filter(F.col("mix") == k).collect()}
        assert len(want) == len(found) == 2  # one word has no pair
        for r in want:
            assert np.allclose(r[2:], found[r.event, r.medium][3:])


@pytest.mark.parametrize("gamma, beta", [(similarity.GAMMA, 0.7), (similarity.GAMMA, 1.0), (0.2, 0.0), (0.9, 0.7)])
def test_only_words_without_a_common_character_are_compared_for_clipping(monkeypatch, gamma, beta):
    rng = np.random.default_rng(8)
    words = sorted({"".join(rng.choice(list("aaaeeeioubcdfghklmnrst"), rng.integers(1, 9))) for _ in range(700)} | {"a" * 90 + "b" * 2, "b", "e" * 40, "éß", "2024"})
    vec = lambda: [None if k == 3 else rng.normal(size=8) for k in range(len(words))]
    told = pd.DataFrame({"word": words, "vec_r": vec(), "vec_d": vec()})
    held = similarity.WordSimilarity(told, beta, gamma)
    monkeypatch.setattr(similarity.WordSimilarity, "HELD_WORDS", 0)
    monkeypatch.setattr(similarity.WordSimilarity, "TILE", 50)
    made = similarity.WordSimilarity(told, beta, gamma)
    member = (rng.random((len(words), 6)) < [0.5, 0.5, 0.9, 1, 0, 0]).astype(float)
    member[7, 4] = member[[0, -1], 5] = 1.0  # a word alone, two words
    want = held.whole @ member
    assert np.allclose(made.signed(member) + made.clipped(member, np.float64), want, rtol=1e-12, atol=1e-10)
    got = made.strengths(member)
    assert np.allclose(got, want * member, rtol=1e-9, atol=0) and ((got > 0) == (want * member > 0)).all()
    size = lambda x: x.stop - x.start if isinstance(x, slice) else len(x)
    share = sum(size(i) * size(j) for i, j, _ in made.apart()) / (len(words) ** 2 / 2)
    assert share < 0.75 or gamma > 0.1


@pytest.mark.parametrize("name, beta", [("sem_beta0", 0.0), ("sem_beta1", 1.0)])
def test_semantic_totals_of_one_corpus_make_no_pair_rows(spark, sf, monkeypatch, name, beta):
    words = queries.p1_words(spark, sf)
    kept = queries._kept(spark, sf, queries.TH, words=frequency.vocabulary(words))
    pairs = similarity.edges(kept, queries.vectors_of(spark, sf, words), queries.SCOPE, beta, only_positive=False)
    want = {r[:2]: r[2:] for r in pairs.groupBy(*queries.SCOPE).agg(F.count("*"), F.sum("sem"), F.max("sem")).collect()}
    monkeypatch.setattr(similarity, "edges", lambda *a, **k: pytest.fail("pairs were made"))
    got = {r[:2]: r[2:] for r in queries.QUERIES[name](spark, sf).collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], rtol=1e-9, atol=1e-5) for k in want)


@pytest.fixture(scope="module")
def few_vectors(tmp_path_factory):
    """The smallest documents beside few vectors, odd ones among them, with and without one that is no number."""
    made = {}
    for nan in (False, True):
        to = tmp_path_factory.mktemp("few")
        (to / "documents.parquet").symlink_to("/root/testdata/sf0.001/documents.parquet")
        rng = np.random.default_rng(3)
        vectors = [(k, rng.normal(size=8).astype("float32").tolist()) for k in range(23) if k != 5] + [(40, [1.0] * 8)]
        vectors[7], vectors[9] = (vectors[7][0], None), (vectors[9][0], [0.0] * 8)
        if nan:
            vectors[11] = (vectors[11][0], [float("nan")] + [1.0] * 7)
        con = duckdb.connect()
        con.execute("CREATE TABLE e (vec_id BIGINT, embedding FLOAT[], label INT)")
        con.executemany("INSERT INTO e VALUES (?, ?, 0)", vectors)
        con.execute(f"COPY e TO '{to}/embeddings.parquet'")
        made[nan] = str(to)
    return made


def as_its_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for table in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf_dir}/{table}.parquet'")
    want = {r[:2]: r[2:] for r in con.execute(queries.SQL[name]).fetchall()}
    got = {r[:2]: r[2:] for r in queries.QUERIES[name](spark, sf_dir).collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], rtol=0, atol=2e-5, equal_nan=True) for k in want)
    return got


def test_sem_beta0_sends_a_series_as_its_distinct_vectors(spark, few_vectors, monkeypatch):
    sent = []
    monkeypatch.setattr(similarity, "_totals", lambda words, *a, go=similarity._totals: (sent.append(words), go(words, *a))[1])
    got = as_its_sql(spark, few_vectors[False], "sem_beta0")
    assert sent[0].count() <= 23 * len(got) < sum(r.n_words for r in sent[0].collect())
    assert np.isnan([v for r in as_its_sql(spark, few_vectors[True], "sem_beta0").values() for v in r]).any()


def test_sem_beta1_is_as_its_sql_over_odd_vectors(spark, few_vectors):
    as_its_sql(spark, few_vectors[False], "sem_beta1")
    assert np.isnan([v for r in as_its_sql(spark, few_vectors[True], "sem_beta1").values() for v in r]).any()


def test_signatures_draw_a_word_once_a_series(spark):
    rows = [("e", m, p, w) for m in "AB" for p in range(1, 9) for w in ("one", "two", f"x{p}")]
    contrib = spark.createDataFrame(rows, "event string, medium string, phase int, word string")
    direct = contrib.withColumn("l", F.explode(F.sequence(F.lit(0), F.lit(63)))).withColumn("z", signatures.gaussian(F.col("word"), F.col("l")))
    want = {}
    for r in direct.groupBy("event", "medium", "phase", "l").agg(F.sum("z").alias("z")).collect():
        want.setdefault(r[:3], [0, 0])[r.l // 63] |= (r.z >= 0) << r.l % 63
    assert {r[:3]: list(r.bits) for r in signatures.sign_projection(contrib).collect()} == want
    drawn_rows = signatures.sign_projection(contrib)._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" in drawn_rows.split("Generate")[-1]  # the phases of a word lie below its numbers


def test_packing_goes_through_the_words_once(spark):
    contrib = spark.createDataFrame([("e", m, p, w) for m in "AB" for p in (1, 2) for w in ("one", "two")], "event string, medium string, phase int, word string")
    series = contrib.select("event", "medium", "phase", F.lit(0.5).alias("pop_norm")).distinct()
    packed = alignment.pack(series, contrib)
    assert len(packed.first().va) == 2
    assert "md5" not in packed._jdf.queryExecution().optimizedPlan().toString()  # one side would draw the numbers again
