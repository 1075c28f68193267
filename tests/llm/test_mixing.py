import re
from collections import defaultdict

from phasewarp.llm import mixing


def water_fill(sizes, cap=3):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: k % 3 + 1 for k, s in enumerate(names)}
    target, capped, total = {}, set(), sum(sizes.values())
    while True:
        left = total - sum(cap * sizes[s] for s in capped)
        open_ = [s for s in names if s not in capped]
        share = {s: left * w[s] / sum(w[x] for x in open_) for s in open_} if open_ else {}
        over = {s for s in open_ if share[s] > cap * sizes[s]}
        if not over:
            return share | {s: cap * sizes[s] for s in capped}
        capped |= over


def test_targets_and_words(spark, make_docs, odd_rows):
    rows = odd_rows + [(100 + k, "w " * (k % 37), f"s{k % 7}") for k in range(400)]
    docs = make_docs(rows)
    got = mixing.copies(docs.withColumnRenamed("target", "t0").withColumn("size", mixing.size_of(docs.text))).collect()
    assert len(got) == len(rows)
    sizes = defaultdict(int)
    for _, t, s in rows:
        sizes[s] += len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    want = water_fill(sizes)
    taken, longest = defaultdict(int), defaultdict(int)
    for r in got:
        assert abs(r.target - want[r.source]) < 1e-6 * max(1, r.target)
        assert 0 <= r.copies <= 3
        taken[r.source] += r.copies * r.size
        longest[r.source] = max(longest[r.source], r.size)
    for s in want:
        assert abs(taken[s] - want[s]) <= 2 * longest[s] + 1


def test_mix_repeats_rows_and_reruns_agree(spark, make_docs, odd_rows):
    docs = make_docs(odd_rows)
    once = sorted(map(str, mixing.mix(docs.drop("target")).collect()))
    assert once == sorted(map(str, mixing.mix(docs.drop("target").repartition(3)).collect()))
    assert mixing.mix(make_docs([]).drop("target")).count() == 0


def test_no_python_in_plan(spark, sf):
    plan = mixing.query(spark, sf)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan
