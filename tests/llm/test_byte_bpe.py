import hashlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from neighborsketch.llm import byte_bpe as bpe

RANKS = bpe.load_ranks(bpe.vocabulary())
CODEC = bpe.Codec(RANKS)
LIBRARY = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=RANKS, special_tokens={})
TEXTS = ["", "'s", "''s 's'll'v're're'st don't  I'LL'd", "a  b\n\n c \t", " \n", "x" * 3000, "ab" * 700 + " " * 500 + "!", "é 12½ 漢字 　 ok  z", "<|endoftext|>", "'", " '", "a'", "'r", "'re", "'l'll", "'" * 999 + "s" * 5000 + "'" + "st" * 3000]


def same(texts):
    got = CODEC.encode(texts)
    assert [np.frombuffer(g, "<u4").tolist() for g in got] == [LIBRARY.encode_ordinary(t) for t in texts]
    assert [d.decode() for d in CODEC.decode(got)] == texts


def test_fixed_texts():
    same(TEXTS)
    for t in TEXTS:
        same([t])


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet="'strevlmdaZ 9\n\t!.é½　-", max_size=25), max_size=5))
def test_random_texts(texts):
    same(texts)


def test_table(spark):
    rows = [(i, t) for i, t in enumerate(TEXTS)] + [(None, None), (3, TEXTS[3])]
    docs = spark.createDataFrame([(a, b, "x") for a, b in rows], "doc_id long, text string, ids string")
    got = sorted(map(repr, bpe.digest(docs, bpe.vocabulary()).collect()))
    assert len(got) == len(rows)
    for r in bpe.digest(docs, bpe.vocabulary()).where("doc_id is not null").collect():
        text = TEXTS[r.doc_id]
        ids = LIBRARY.encode_ordinary(text)
        assert (r.n_tokens, r.ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert r.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()
    back = {r.doc_id: r.text for r in bpe.decode(bpe.encode(docs, bpe.vocabulary()), bpe.vocabulary()).collect() if r.doc_id is not None}
    assert back == dict(enumerate(TEXTS))
    assert bpe.digest(docs.limit(0), bpe.vocabulary()).count() == 0
