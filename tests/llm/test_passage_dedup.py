import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from phasewarp.llm import passage_dedup as pd_
from phasewarp.llm.common import shared_folder


def prose(rng, n):
    return [rng.choice("abcdefghij") + str(rng.randrange(3000)) for _ in range(n)]


def test_every_long_passage_holds_a_common_piece():
    rng = random.Random(7)
    h = pd_.WordHashes()
    for _ in range(60):
        passage = prose(rng, 50)
        cut = []
        for _ in range(2):
            text = " ".join(prose(rng, rng.randrange(0, 60)) + passage + prose(rng, rng.randrange(0, 60)))
            key, start, words, unit, bands = pd_.text_units([(1, "x y z\n" + text), (2, text.upper())], h)
            assert len(bands) == 2 and unit[0] == unit[1] and (bands[0] == bands[1]).all()
            assert start[start >= 0].min() >= 0 and set(words[start == pd_.WHOLE].tolist()) == {len(text.split()), len(text.split()) + 3}
            cut.append(set(unit[(words == pd_.PIECE) & (start >= 0)].tolist()))
        assert cut[0] & cut[1]


def test_anchor_definition():
    rng = np.random.default_rng(1)
    for n in (5, 6, 40):
        g = rng.integers(0, 9, n, dtype=np.uint64)
        want = set()
        for s in range(n - 4):
            w = g[s : s + 5].tolist()
            want.add(s + max(i for i, x in enumerate(w) if x == min(w)))
        assert set(pd_.anchors(g, 5, np.arange(n - 4)).tolist()) == want
    assert len(pd_.anchors(g, 5, np.arange(0))) == 0


@pytest.fixture(scope="module")
def near_lines():
    rng = random.Random(8)
    out = []
    for _ in range(12):
        base = prose(rng, rng.randrange(50, 110))
        for _ in range(8):
            line = list(base)
            for _ in range(rng.randrange(0, 5)):
                line[rng.randrange(len(line))] = "changed" + str(rng.randrange(99))
            out.append(" ".join(line))
    return out


def shingles(line):
    w = line.lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def test_links_cluster_as_brute_force(spark, near_lines):
    docs = spark.createDataFrame(list(enumerate(near_lines)), "doc_id long, text string")
    sets = [shingles(x) for x in near_lines]
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(sets)), 2):
        if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
            a, b = sorted((find(i), find(j)))
            root[b] = a
    want = {frozenset(i for i in range(len(sets)) if find(i) == r) for r in {find(i) for i in range(len(sets))}}
    for crowd in (64, 2):
        folder = shared_folder(spark)
        keyed = docs.withColumnRenamed("doc_id", "key")
        units = pd_.stored(keyed.mapInArrow(pd_._unit_batches, pd_.UNITS), folder, "units").filter("size(bands) > 0")
        of = {r.unit: r.key for r in units.collect()}
        met = pd_.Candidates(units, folder, crowd)
        wanted = units.dropDuplicates(["unit"]).groupBy("key").agg(F.collect_list(F.struct("start", "words", "unit")).alias("wanted"))
        asked = keyed.join(wanted, "key").select("key", "text", F.array().cast("array<int>").alias("hits"), "wanted")
        sets_ = asked.mapInArrow(pd_._detail_batches, pd_.DETAIL).filter("unit IS NOT NULL").select("unit", "shingles")
        links = met.links(sets_, 0.8).collect()
        assert all(len(sets[of[r.a]] & sets[of[r.b]]) >= 0.8 * len(sets[of[r.a]] | sets[of[r.b]]) for r in links)
        roots = {n.node: n.root for n in pd_.components(spark.createDataFrame(links), shared_folder(spark)).collect()}
        by_text = {}
        for r in units.collect():
            by_text.setdefault(roots.get(r.unit, r.unit), set()).add(r.key)
        assert {frozenset(v) for v in by_text.values()} == want


def runs_of(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 50]): i for i in range(len(w) - 49)}


def test_classes_and_spans_as_brute_force(make_docs, odd_rows):
    """Passages of 40 to 80 words across line breaks, inside one document too, against all runs of 50 words."""
    rng = random.Random(11)
    passages = [prose(rng, n) for n in (40, 49, 50, 51, 60, 80, 80)]
    rows = []
    for k in range(60):
        words = prose(rng, 130)
        for p in rng.sample(passages, rng.choice((0, 0, 1, 2))):
            at = rng.randrange(len(words))
            words[at:at] = p
        if k == 7:
            words += passages[5] + ["between"] + passages[5]
        lines, at = [], 0
        while at < len(words):  # lines too short to be paragraphs of their own
            n = rng.randrange(5, 40)
            lines.append(" ".join(words[at : at + n]))
            at += n
        rows.append((500 - k, "\n".join(lines), "s"))
    rows += [(600, rows[3][1].upper(), "s"), (601, " ".join(prose(rng, 20)), "s"), (602, "short " * 3, "s"), (603, "short " * 3, "s")]
    by_run = {}
    for i, text, _ in sorted(rows):
        w = text.lower().split()
        for at in range(len(w) - 49):
            by_run.setdefault(tuple(w[at : at + 50]), []).append((i, at))
    root = {i: i for i, _, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    gone = {i: set() for i in root}
    for places in by_run.values():
        for i, at in places[1:]:
            a, b = sorted((find(places[0][0]), find(i)))
            root[b] = a
            gone[i] |= set(range(at, at + 50))
    got = {r.doc_id: r for r in pd_.document_classes(make_docs(rows)).collect()}
    assert len(got) == len(rows)
    for i in root:
        assert got[i].class_id == find(i), i
        have = {w for s in got[i].removed for w in range(s.start, s.stop)}
        assert got[i].removed_words == len(have) == sum(s.stop - s.start for s in got[i].removed)
        assert have == (gone[i] if i != 600 else set(range(got[i].removed_words))), i
    assert got[600].removed_words == len(rows[3][1].split())
    same = pd_.document_classes(make_docs([(1, " ".join(prose(rng, 60)), "s")] * 3 + [(None, " ".join(prose(rng, 80)), "s") for _ in range(2)])).collect()
    assert len(same) == 5 and sorted(r.removed_words > 0 for r in same if r.doc_id == 1) == [False, True, True]


def test_planted_passages_are_caught_and_clean_documents_left(spark, make_docs, odd_rows):
    rng = random.Random(9)
    passage = prose(rng, 55)
    rows = []
    for k in range(40):
        words = prose(rng, 200)
        if k % 4 == 0:
            at = rng.randrange(100, 200)
            words[at:at] = passage
        rows.append((100 + k, " ".join(words[:100]) + "\n" + " ".join(words[100:]), "s"))
    got = {r.doc_id: r for r in pd_.document_classes(make_docs(rows)).collect()}
    assert all(got[100 + k].repeated and got[100 + k].class_id == 100 for k in range(0, 40, 4))
    assert all(not got[100 + k].repeated and got[100 + k].class_id == 100 + k for k in range(40) if k % 4)
    assert got[100].removed_words == 0 and got[104].removed_words == 55
    assert pd_.document_classes(make_docs([])).count() == 0
    assert pd_.document_classes(make_docs(odd_rows)).count() == len(odd_rows)
