import zlib

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from phasewarp.llm import token_orc as to
from phasewarp.llm.common import shared_folder

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_round_trip_against_the_library(spark, make_docs, odd_rows):
    t = Tokenizer.from_file(PATH)
    folder = f"{shared_folder(spark)}/t.orc"
    to.write_tokens(make_docs(odd_rows), PATH, folder, parts=3)
    got = sorted(to.digest(spark, folder).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in got] == sorted((i for i, _, _ in odd_rows), key=lambda i: (i is not None, i or 0))
    start = 0
    by_id = {}
    for i, text, _ in odd_rows:
        ids = t.encode(text or "", add_special_tokens=False).ids + [1]
        by_id[i] = (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    for r in got:
        assert (r.n_tokens, r.ids_crc32) == by_id[r.doc_id] and r.start == start
        start += r.n_tokens
    assert [r.doc_id for r in to.lookup(spark, folder, [7, 999]).collect()] == [7]
    assert sorted(r.doc_id for r in to.read_range(spark, folder, 4, 6).collect()) == [4, 4, 5, 6]


def test_filters_reach_the_files(spark, make_docs, odd_rows):
    folder = f"{shared_folder(spark)}/t.orc"
    to.write_tokens(make_docs(odd_rows), PATH, folder)
    assert "PushedFilters: [IsNotNull(doc_id)" in to.read_range(spark, folder, 4, 6)._jdf.queryExecution().toString().replace("In(doc_id", "")


def test_cache_turnover_keeps_ids(monkeypatch):
    monkeypatch.setattr(to, "CACHE_CHUNKS", 5)
    e, t = to.ChunkEncoder(PATH), Tokenizer.from_file(PATH)
    for text in ("a b c d", "e f g h i j k l", "a b z", ""):
        assert np.frombuffer(e(text), "<u4").tolist() == t.encode(text, add_special_tokens=False).ids


def test_empty(spark, make_docs):
    folder = f"{shared_folder(spark)}/t.orc"
    to.write_tokens(make_docs([]), PATH, folder)
    assert to.digest(spark, folder).count() == 0
