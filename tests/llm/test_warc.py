import base64
import gzip
import hashlib
import random

from phasewarp.llm import warc
from phasewarp.llm.common import shared_folder


def test_loser_tree():
    random.seed(2)
    for k in (0, 1, 2, 3, 5, 8, 13):
        runs = [sorted(random.randrange(50) for _ in range(random.randrange(9))) for _ in range(k)]
        assert list(warc.LoserTree([iter(r) for r in runs])) == sorted(x for r in runs for x in r)


PAGES = [
    (1, "http://www.A.example/x", "<p>one</p>"),
    (2, "http://a.example/y?q=1", "<p>two</p>"),
    (3, "https://b.example/\nz", "<p>one</p>"),
    (4, None, None),
    (5, "http://a.example/x", ""),
    (6, "http://c.example", "é" * 70_000),
    (2, "http://a.example/y?q=1", "<p>two</p>"),
    (None, "http://n.example", "<p>one</p>"),
    (7, "http://a.example/x", "<p>one</p>"),
]


def brute(rows, least=0):
    out = []
    first = {}
    for i, _, h in rows:
        b = (h or "").encode()
        if i is not None:
            first[b] = min(first.get(b, i), i)
    used = set()
    for i, _, h in rows:
        b = (h or "").encode()
        response = len(b) < least or (first.get(b) == i and b not in used)
        if first.get(b) == i:
            used.add(b)
        out.append((i, len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if response else "revisit", None if response else first.get(b)))
    return sorted(out, key=str)


def run(spark, rows, least=0, **kw):
    folder = shared_folder(spark)
    runs = warc.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("run", warc.F.lit(1)), folder, least, **kw)
    return runs, warc.read_archives(runs, folder), folder


def test_records(spark):
    for least in (0, 11):
        _, back, _ = run(spark, PAGES, least)
        got = sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in back.collect()), key=str)
        assert got == brute(PAGES, least)
    assert run(spark, [])[1].count() == 0


def test_archives_roll_and_histories_are_sorted(spark):
    runs, back, folder = run(spark, PAGES, archive_bytes=300)
    assert back.count() == len(PAGES)
    assert runs.select("run").distinct().count() > 3
    got = sorted(warc.histories(runs, 3).collect(), key=lambda r: (r.part, r.pos))
    assert len(got) == len(PAGES)
    assert [(r.urlkey, r.captured) for r in got] == sorted((r.urlkey, r.captured) for r in got)
    name = runs.first().run
    with open(f"{folder.removeprefix('file://')}/archives/{name}", "rb") as f:
        assert gzip.decompress(f.read()).startswith(b"WARC/1.1\r\n")


def test_query(spark, sf):
    rows = [(r.page_id, r.url, r.html) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    got = sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.query(spark, sf).collect()), key=str)
    assert got == brute(rows)
