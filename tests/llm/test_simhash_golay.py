import itertools
import random

import numpy as np
import xxhash

from phasewarp.llm import simhash_golay as sg


def slow_print(text):
    import re

    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def brute_components(prints):
    ids = sorted(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(ids, 2):
        if bin(prints[a] ^ prints[b]).count("1") <= 2:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: find(i) for i in ids}


def test_codewords_within_four_bits():
    rng = np.random.default_rng(3)
    words = rng.integers(0, 1 << 23, 300)
    rows, keys = sg.codeword_keys(words)
    for k, w in enumerate(words):
        mine = set(keys[rows == k].tolist())
        assert len(mine) in (1, 6)
        for a, b in [(0, 0), *itertools.combinations(range(23), 2)]:
            near = int(w) ^ (1 << a) ^ (1 << b)
            _, other = sg.codeword_keys(np.array([near]))
            assert mine & set(other.tolist())
        if k > 25:
            break


def test_fingerprints(odd_rows):
    for _, t, _ in odd_rows:
        assert sg.fingerprint(t) == slow_print(t)


def test_links_match_brute_force_cool_and_hot(spark):
    random.seed(5)
    base = [random.getrandbits(64) for _ in range(30)] + [0]
    prints = set(base)
    for b in base[:6] + [0]:
        x = b
        for _ in range(25):
            x ^= 1 << random.randrange(64)
            if random.random() < 0.5:
                x ^= 1 << random.randrange(64)
            prints.add(x)
    signed = [p - 2**64 if p >= 2**63 else p for p in prints]
    frame = spark.createDataFrame([(p,) for p in signed], "fp long")
    from phasewarp.llm.common import components, shared_folder

    want = brute_components({p: p % 2**64 for p in signed})
    classes = lambda m: {frozenset(k for k in m if m[k] == r) for r in set(m.values())}
    for hot in (200, 2):
        links = sg.links(frame, shared_folder(spark), hot)
        got = {p: p for p in signed} | {r.node: r.root for r in components(links, shared_folder(spark)).collect()}
        assert classes(got) == classes(want)


def test_groups_and_keep_one(make_docs, odd_rows):
    docs = make_docs(odd_rows)
    got = {r.doc_id: r for r in sg.near_groups(docs).collect()}
    assert got[1].fingerprint == "0" * 16
    assert got[3].component_id is None  # the row without an id has the same text
    assert got[2].component_id == got[1].component_id == got[5].component_id
    kept = sg.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None)[:1] == [1]
    assert sg.near_groups(make_docs([])).count() == 0


def test_keep_one_keeps_a_row_of_every_group_without_ids_of_its_own(make_docs):
    rng = random.Random(11)
    texts = [" ".join(f"w{rng.randrange(10_000)}" for _ in range(60)) for _ in range(6)]
    prints = [slow_print(t) for t in texts]
    assert min(bin(a ^ b).count("1") for a, b in itertools.combinations(prints, 2)) > 2
    rows = [(None, texts[0], "s"), (None, texts[1], "s"), (None, texts[1].upper(), "s"), (7, texts[2], "s"), (7, texts[3], "s"), (7, texts[3], "s")]
    rows += [(8, texts[4], "s"), (None, texts[4], "s"), (9, texts[5], "s"), (None, None, "s"), (None, "", "s")]
    kept = [(r.doc_id, (r.text or "").lower()) for r in sg.keep_one(make_docs(rows)).collect()]
    want = [(None, ""), (None, texts[0]), (None, texts[1]), (7, texts[2]), (7, texts[3]), (None, texts[4]), (9, texts[5])]
    assert sorted(kept, key=str) == sorted(want, key=str)


def jaccard_classes(texts, shingle=5, least=0.8):
    """Classes of lower-cased texts by exact similarity of all pairs."""
    sets = {}
    for t in texts:
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or ""))
        words = low.encode().split()
        sets[low] = {tuple(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))}
    root = {t: t for t in sets}

    def find(t):
        while root[t] != t:
            t = root[t]
        return t

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both >= least * (len(sets[a]) + len(sets[b]) - both):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {t: find(t) for t in sets}


def test_similar_groups_match_brute_force_on_edited_texts(make_docs):
    rng = random.Random(23)
    rows, words = [], [f"w{k}" for k in range(4000)]
    for family in range(12):
        base = [rng.choice(words) for _ in range(rng.choice((40, 120, 400)))]
        for copy in range(1 if family < 4 else 14):
            text = list(base)
            for _ in range(rng.randrange(0, max(2, len(base) // 40))):
                text[rng.randrange(len(text))] = rng.choice(words)
            rows.append((len(rows), " ".join(text), "s"))
    rows += [(len(rows) + k, t, "s") for k, t in enumerate((None, "", " \n", "one two", "One Two", "one two three"))]
    want = jaccard_classes([t for _, t, _ in rows])
    low = lambda t: (t or "").lower()  # noqa: E731  (the texts are ASCII)
    first = {}
    for i, t, _ in rows:
        first.setdefault(want[low(t)], i)
    assert 12 < len(first) < len(rows) / 2
    for crowd in (64, 2):
        docs = make_docs(rows)
        found = {r.unit: r.root for r in sg.similar_groups(docs, crowd=crowd).collect()}
        units = sg._named(docs).select("unit", "text").collect()
        got = {low(r.text): found.get(r.unit, r.unit) for r in units}
        classes = lambda m: {frozenset(t for t in m if m[t] == r) for r in set(m.values())}
        assert classes(got) == classes(want)
    assert sorted(r.doc_id for r in sg.keep_one(docs).collect()) == sorted(first.values())
    assert sg.keep_one(make_docs([])).count() == 0


def test_similar_groups_match_brute_force_on_the_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = [r.text for r in docs.select("text").collect()]
    want = jaccard_classes(texts)
    kept = [r.text for r in sg.keep_one(docs).collect()]
    assert len(kept) == len(set(want.values())) < len(texts)


def test_table_matches_brute_force(spark, sf):
    rows = sg.query(spark, sf).collect()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    prints = {i: slow_print(t) for i, t in texts.items()}
    want = brute_components(prints)
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in rows} == {i: (f"{p:016x}", want[i]) for i, p in prints.items()}
