import itertools
import random

import pytest

from phasewarp.llm import line_dedup as ld


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def mutate(rng, s, n):
    for _ in range(n):
        k = rng.randrange(len(s) + 1)
        s = rng.choice([s[:k] + rng.choice("abcdé ") + s[k:], s[:k] + s[k + 1 :], s[:k] + rng.choice("xyz") + s[k + 1 :]])
    return s


def test_banded_distance_equals_the_definition():
    rng = random.Random(4)
    for _ in range(3000):
        a = "".join(rng.choice("abc") for _ in range(rng.randrange(0, 30)))
        b = mutate(rng, a, rng.randrange(0, 6)) if rng.random() < 0.8 else "".join(rng.choice("abc") for _ in range(rng.randrange(0, 30)))
        for tau in (1, 2, 3):
            assert ld.edits_within(a, b, tau) == (distance(a, b) <= tau), (a, b, tau)


def near(a, b):
    return distance(a, b) <= ld.allowed(min(len(a), len(b)))


def test_near_lines_share_a_key():
    rng = random.Random(5)
    for _ in range(600):
        a = "".join(rng.choice("abcdef") for _ in range(rng.randrange(10, 70)))
        b = mutate(rng, a, rng.randrange(0, 3))
        short, long_ = sorted((a, b), key=len)
        if a != b and near(a, b) and ld.allowed(len(short)):
            assert set(ld.index_keys(short)) & set(ld.probe_keys(long_))
            if len(a) == len(b):
                assert set(ld.index_keys(long_)) & set(ld.probe_keys(short))


@pytest.fixture(scope="module")
def lines():
    rng = random.Random(6)
    out = set()
    for _ in range(30):
        base = "".join(rng.choice("abcdefghij ") for _ in range(rng.choice((5, 11, 12, 14, 22, 24, 25, 30, 60))))
        out |= {mutate(rng, base, rng.randrange(0, 4)) for _ in range(12)}
    return sorted(x for x in out if x)


def test_links_and_classes_match_brute_force(make_docs, lines, monkeypatch):
    want = {(i, j) for (i, a), (j, b) in itertools.combinations(enumerate(lines), 2) if near(a, b)}
    assert len(want) > 100
    root = list(range(len(lines)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in want:
        a, b = sorted((find(i), find(j)))
        root[b] = a
    docs = make_docs([(k, "\n".join(lines[k * 7 : k * 7 + 7]), "s") for k in range(-(-len(lines) // 7))])
    for block, held in ((ld.BLOCK, ld.HELD_ROWS), (3, 2)):
        monkeypatch.setattr(ld, "BLOCK", block)
        monkeypatch.setattr(ld, "HELD_ROWS", held)
        got = {r.doc_id * 7 + r.line_no: r for r in ld.line_classes(docs).collect()}
        assert len(got) == len(lines)
        for k in range(len(lines)):
            assert got[k].links == sum(k in pair for pair in want), lines[k]
            assert got[k].class_doc * 7 + got[k].class_line == find(k), lines[k]


def test_live_runs_stream():
    rng = random.Random(12)
    rows = sorted((rng.randrange(40), rng.randrange(2), rng.randrange(60)) for _ in range(900)) + [(99, 0, 1), (99, 1, 1)] + [(100, 1, k) for k in range(50)]
    by_key = {}
    for k, s, x in rows:
        by_key.setdefault(k, set()).add((s, x))
    want = {(k, s, x) for k, v in by_key.items() if any(s == 0 for s, _ in v) and len({x for _, x in v}) > 1 for s, x in v}
    for size in (1, 7, 100, 2000):
        for held in (5, 10_000):
            ld.HELD_ROWS, before = held, ld.HELD_ROWS
            parts = [ld._longs(["key", "side", "lid"], list(zip(*rows[k : k + size]))) for k in range(0, len(rows), size)]
            got = [tuple(r.values()) for b in ld._live_batches(parts) for r in b.to_pylist()]
            ld.HELD_ROWS = before
            assert set(got) == want


def test_classes(spark, make_docs, odd_rows):
    a, b, c = "the quick brown fox jumps over it", "the quick brown fox jumped over it", "something else entirely different"
    rows = [(1, f"{a}\nshort\n{c}", "s"), (2, f"{b}\nshort", "s"), (2, f"{b}\nshort", "s"), (3, c, "s"), *odd_rows[:3]]
    got = sorted((r.doc_id, r.line_no, r.class_doc, r.class_line, r.links, r.kept) for r in ld.line_classes(make_docs(rows[:4])).collect())
    assert got == [
        (1, 0, 1, 0, 1, True), (1, 1, 1, 1, 0, True), (1, 2, 1, 2, 0, True),
        (2, 0, 1, 0, 1, False), (2, 0, 1, 0, 1, False), (2, 1, 1, 1, 0, False), (2, 1, 1, 1, 0, False),
        (3, 0, 1, 2, 0, False),
    ]
    assert ld.line_classes(make_docs([])).count() == 0
    assert ld.line_classes(make_docs(odd_rows)).count() == sum(0 if t is None else t.count("\n") + 1 for _, t, _ in odd_rows)
