import hashlib

import numpy as np

from phasewarp.llm import exact_dedup as ed


def test_filter_has_no_false_negatives_and_few_false_positives():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 3, 10, 100, 5_000, 60_000):
        keys = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        f = ed.build_filter(keys)
        assert ed.probe_filter(keys, *f).all()
        others = rng.integers(2**63, 2**64 - 1, 20_000, dtype=np.uint64)
        assert ed.probe_filter(others, *f).mean() < 0.02


def test_decisions_match_brute_force(make_docs, odd_rows):
    lower = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or ""))
    got = ed.decide(make_docs(odd_rows)).collect()
    assert len(got) == len(odd_rows)
    groups = {}
    for i, t, _ in odd_rows:
        groups.setdefault(lower(t), []).append(i)
    for r in got:
        ids = next(v for k, v in groups.items() if hashlib.sha256(k.encode()).hexdigest() == r.text_sha256 and r.doc_id in v)
        assert r.group_size == len(ids)
        assert r.keep_id == max((i for i in ids if i is not None), default=None)
    assert sum(r.kept for r in got) == len(groups)


def test_any_split_gives_the_same(make_docs, odd_rows):
    docs = make_docs(odd_rows)
    cols = ["doc_id", "keep_id", "group_size", "kept", "text_sha256"]
    wanted = sorted(map(str, ed.decide(docs).select(cols).collect()))
    for split in (-1, 4, 1000):
        assert sorted(map(str, ed.decide(docs, split).select(cols).collect())) == wanted


def test_empty_and_keep_one(make_docs, odd_rows):
    assert ed.decide(make_docs([])).count() == 0
    docs = make_docs(odd_rows)
    kept = ed.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == [2, 4, 5, 6, 7, 8, 9, 10, 11]
