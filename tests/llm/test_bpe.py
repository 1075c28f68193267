import hashlib

import numpy as np
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from phasewarp.llm import bpe

PATH = public_tokenizers.path("byte_bpe_50k.json")
LIB = Tokenizer.from_file(PATH)


def ids(text):
    return np.frombuffer(bpe.model(PATH).encode(text), "<i4").tolist()


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.sampled_from(list("abcdeth inrsou'lv \n\t0123.,!é你   <|>endoftext")), max_size=60))
def test_any_text_encodes_as_the_library(text):
    assert ids(text) == LIB.encode(text, add_special_tokens=False).ids


@settings(max_examples=100, deadline=None)
@given(st.text(max_size=40))
def test_unicode(text):
    want = LIB.encode(text, add_special_tokens=False).ids
    assert ids(text) == want
    assert bpe.model(PATH).decode(np.array(want, np.int64)).decode("utf-8", "replace") == LIB.decode(want, skip_special_tokens=False)


def test_backtracking_equals_merging():
    m = bpe.model(PATH)
    for word in (b"aaaaaaaaaaaaaaaaaaaaaaaa", b" unbelievably", b"thththththinging", b"\xff\xfe\x00", b"reonationality" * 4):
        assert m.encode_piece(word) == m.merge(word)


def test_invalid_bytes_decode_with_replacement():
    m = bpe.model(PATH)
    one = m.id_of[b"\xe4"]
    assert m.decode(np.array([one])).decode("utf-8", "replace") == LIB.decode([one])


def test_table(spark, make_docs, odd_rows):
    docs = make_docs(odd_rows).withColumnRenamed("target", "n_tokens")
    back = bpe.decode(bpe.encode(docs, PATH), PATH).collect()
    assert len(back) == len(odd_rows)
    for r in back:
        want = LIB.encode(r.text or "", add_special_tokens=False).ids
        assert r.ids == want and r.decoded == LIB.decode(want, skip_special_tokens=False)
    assert bpe.encode(make_docs([]), PATH).count() == 0


def test_query(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in bpe.query(spark, sf).collect():
        want = LIB.encode(texts[r.doc_id] or "", add_special_tokens=False).ids
        assert r.n_tokens == len(want)
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(LIB.decode(want, skip_special_tokens=False).encode()).hexdigest()
