import numpy as np
import pytest

from phasewarp.llm import toxicity as tx


def test_fold_agrees_with_zlib(spark):
    frame = spark.range(50).withColumnRenamed("id", "doc_id")
    for r in frame.select("doc_id", tx.held_out(frame.doc_id).alias("h")).collect():
        assert r.h == (tx.crc_fold(r.doc_id) == 2)


@pytest.fixture(scope="module")
def trained(spark):
    good = "the quick brown fox jumps over lazy dogs while reading a stupid tall tale of idiots stupid people say".replace("stupid", "sunny").replace("idiots", "ideas")
    rows, labels = [], []
    for k in range(400):
        toxic = k % 4 == 0
        rows.append((k, f"{good} {k} " + ("you stupid idiot" if toxic else "my friend")))
        labels.append((k, 1, int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_obfuscated_words_score_as_restored(spark, trained):
    scorer = tx.fit(*trained)
    for bad in ("you stupid idiot", "st.u.p.i.d", "$tupid person", "stuuuupid", "s t u p i d ok", "id1ot", "1diot"):
        assert scorer(bad) > tx.THRESHOLD, bad
    spaced = " ".join("readingtalesofmanylazydogsandfriendsandpeopleandfoxesandmoreyoustupidperson")
    for bad in (spaced, "s" + "." * 90 + "tupid", "st" + "u" * 200 + "pid"):
        assert scorer(bad) > tx.THRESHOLD, bad
    for fine in (None, "", "my friend 123", "2.0.1", "a b c d e", "x" * 50_000, "!!!"):
        assert scorer(fine) < tx.THRESHOLD, fine


def test_rejects_and_keeps_columns(spark, trained, make_docs, odd_rows):
    scorer = tx.fit(*trained)
    docs = make_docs([*odd_rows, (50, "stupid stupid idiot", "a")])
    kept = tx.reject(docs, scorer)
    assert kept.columns == docs.columns and kept.count() == len(odd_rows)
    assert tx.score(docs, scorer, ["doc_id"]).count() == len(odd_rows) + 1
    assert tx.reject(make_docs([]), scorer).count() == 0


def test_without_labels(spark, trained, make_docs, odd_rows):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert tx.fit(make_docs(odd_rows), none)("stupid") < 1e-3


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{d}/labels.parquet").select("doc_id", "toxic")
    got = tx.query(spark, d).join(labels, "doc_id").toPandas()
    fresh = got[got.held_out]
    assert got.score.between(0, 1).all() and set(got.predicted) <= {0, 1}
    right = (fresh.predicted == fresh.toxic).mean()
    assert right >= max(0.9, 1 - fresh.toxic.mean()) and np.corrcoef(fresh.score, fresh.toxic)[0, 1] > 0.5
