import hashlib
from collections import Counter

import numpy as np
import pytest

from phasewarp.llm import weighted_sampling as ws

import xxhash


def xx(value, seed=42):
    return xxhash.xxh64_intdigest(value, seed)


def slow_slots(text):
    words = Counter((text or "").split())
    u = lambda h, at: ((h >> at & (2**31 - 1)) + 0.5) / 2**31
    out = []
    for slot in range(ws.BINS):
        drawn = [(1 << 62, 0)]
        for word, n in words.items():
            x = xxhash.xxh64_intdigest(xx(word.encode()).to_bytes(8, "little"), 42)
            one, two = (xxhash.xxh64_intdigest(k.to_bytes(4, "little"), x) for k in (2 * slot + 1, 2 * slot + 2))
            r, c, b = -np.log(u(one, 0) * u(one, 31)), np.log(-np.log(u(two, 0) * u(two, 31))), u(one ^ two, 17)
            t = int(np.floor(np.log(float(n)) / r + b))
            drawn.append((c - r * (t - b + 1), xxhash.xxh64_intdigest(t.to_bytes(8, "little", signed=True), x) & 65535))
        out.append(min(drawn)[1])
    return out


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(2)
    vocabulary = [f"w{k}" for k in range(900)]
    texts = [" ".join(rng.choice(vocabulary, rng.integers(150, 500))) for _ in range(25)]
    return [(k * 3, t, "s") for k, t in enumerate(texts)] + [(200, None, "s"), (201, "", "s"), (202, "one", "s"), (202, "one", "s"), (None, "é ü x", "s"), (300, "long " * 20_000, "s")]


def test_matches_brute_force(make_docs, rows):
    got = ws.compare(make_docs(rows), parts=3).collect()
    assert len(got) == len(rows)
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0)))
    by = {}
    for r, after in zip(order, order[1:] + order[:1]):
        t, nxt = r[1] or "", after[1] or ""
        k = len(t) // 3
        by.setdefault(r[0], []).append((t, t[: len(t) - k] + nxt[:k], nxt))
    exact = total = 0
    for g in got:
        # rows with one id and text come in either order
        t, edited, nxt = next((v for v in by[g.doc_id] if hashlib.sha256(v[1].encode()).hexdigest() == g.edited_sha256), by[g.doc_id][0])
        assert g.n_chars == len(t) and g.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        want = [f"{v:04x}" for v in slow_slots(t)]
        have = [g.fingerprint[4 * k : 4 * k + 4] for k in range(ws.BINS)]
        exact += sum(a == b for a, b in zip(want, have))
        total += ws.BINS
        other = [g.edited_fingerprint[4 * k : 4 * k + 4] for k in range(ws.BINS)]
        assert g.near_edited == sum(a == b for a, b in zip(have, other)) / ws.BINS
    assert exact >= 0.999 * total


def test_collision_rate_is_the_generalised_jaccard(make_docs, rows):
    texts = {r[0]: r[1] for r in rows[:25]}
    ids = sorted(texts, reverse=True)
    gaps = []
    for g in ws.compare(make_docs(rows[:25]), parts=2).collect():
        nxt = texts[ids[(ids.index(g.doc_id) + 1) % len(ids)]]
        t = texts[g.doc_id]
        k = len(t) // 3
        a, b = Counter(t.split()), Counter((t[: len(t) - k] + nxt[:k]).split())
        gaps.append(g.near_edited - sum((a & b).values()) / sum((a | b).values()))
    assert abs(np.mean(gaps)) < 0.04 and np.std(gaps) < 0.1


def test_query_estimates_skewed_and_short_texts(spark, make_docs, tmp_path):
    rows, likeness = [], {}
    for k in range(0, 80, 2):
        if k < 40:
            pair = ["same " * 1000 + " ".join(f"{side}{k}x{j}" for j in range(63)) for side in "ab"]
        else:
            pair = [f"p{k} p{k} p{k} q{k} {side}{k}" for side in "ab"]
        rows += [(k + 1, pair[0], "s"), (k, pair[1], "s")]
        a, b = map(Counter, map(str.split, pair))
        likeness[k + 1] = sum((a & b).values()) / sum((a | b).values())
    rows += [(200, None, "s"), (201, " ", "s")]
    make_docs(rows).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in ws.query(spark, str(tmp_path)).collect()}
    assert len(got) == len(rows) and got[200].fingerprint == got[201].fingerprint == "0" * 256
    for of in (range(1, 40, 2), range(41, 80, 2)):
        gaps = [got[k].near_next - likeness[k] for k in of]
        assert abs(np.mean(gaps)) < 0.05 and np.std(gaps) < 0.12
    right = [f"{a:04x}" == got[i].fingerprint[4 * k : 4 * k + 4] for i, t, _ in rows for k, a in enumerate(slow_slots(t))]
    assert np.mean(right) >= 0.999


def test_plan_is_native_and_empty_is_empty(spark, sf, make_docs):
    plan = ws.query(spark, sf)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan
    assert ws.compare(make_docs([]), parts=2).count() == 0
