import hashlib

import numpy as np
import public_tokenizers as tok
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from nudgegraph.llm.bpe import Coder, PerfectHash, bpe_decode, bpe_digests, bpe_encode, read_ranks, vocabulary

PATH = tok.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def coder():
    return Coder(*vocabulary(PATH), tok.PATTERN)


@pytest.fixture(scope="module")
def other():
    return tiktoken.Encoding("own", pat_str=tok.PATTERN, mergeable_ranks=read_ranks(PATH), special_tokens={})


def test_perfect_hash_is_minimal():
    keys = [b"k%d" % i for i in range(5000)]
    table = PerfectHash(keys)
    assert sorted(table.key_at) == list(range(5000)) and (table.find(keys) == np.arange(5000)).all()


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=80))
def test_same_ids(coder, other, text):
    assert coder.encode(text) == other.encode_ordinary(text)
    assert coder.decode(coder.encode(text)) == text.encode()


def test_long_words(coder, other):
    for text in ("a" * 20_000, "ab" * 9000 + "!" * 5000, " " * 3000):
        assert coder.encode(text) == other.encode_ordinary(text)


def test_frames(spark, odd, none, other):
    out = {r.doc_id: r for r in bpe_digests(odd, PATH, tok.PATTERN).collect()}
    for doc_id, text in ((r.doc_id, r.text or "") for r in odd.collect()):
        ids = other.encode_ordinary(text)
        assert out[doc_id].n_tokens == len(ids) and out[doc_id].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert out[doc_id].decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()
    back = {r.doc_id: r.bytes for r in bpe_decode(bpe_encode(odd, PATH, tok.PATTERN), PATH, tok.PATTERN).collect()}
    assert all(bytes(back[r.doc_id]) == (r.text or "").encode() for r in odd.collect())
    assert bpe_digests(none, PATH, tok.PATTERN).count() == 0
