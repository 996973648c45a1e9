import hashlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from claimloom.llm import byte_bpe, token_counts

from . import edge_cases


@pytest.fixture(scope="module")
def codec():
    return byte_bpe.default_codec()


def library():
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.load_ranks(P.path("byte_bpe_50k.tiktoken")), special_tokens={})


def test_perfect_hash_is_minimal_and_exact():
    keys = [f"k{i}".encode() for i in range(3000)]
    h = byte_bpe.PerfectHash(keys)
    assert sorted(h.slot(k) for k in keys) == list(range(3000))
    assert all(h.slot(f"other{i}".encode()) == -1 for i in range(500))
    assert byte_bpe.PerfectHash([]).slot(b"x") == -1


def test_byte_bpe_equals_library(spark, codec):
    lib = library()
    got = {r.doc_id: r for r in byte_bpe.encode_decode(edge_cases.frame(spark), codec, ids=True).collect()}
    rows = edge_cases.rows()
    assert len(got) == len(rows)
    for doc_id, text, *_ in rows:
        ids = lib.encode_ordinary(text or "")
        assert got[doc_id].ids == ids and got[doc_id].n_tokens == len(ids)
        assert got[doc_id].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[doc_id].decoded_sha256 == hashlib.sha256((text or "").encode()).hexdigest()
    assert byte_bpe.encode_decode(edge_cases.empty(spark), codec).count() == 0


def test_long_text_slices_join_again(codec):
    text = " ".join(f"word{i}  x\n" if i % 7 == 0 else f"it's{i}" for i in range(4000))
    assert "".join(byte_bpe.slices(text, 100)) == text
    lib = library()
    assert [i for s in byte_bpe.slices(text, 100) for i in codec.encode(s)] == lib.encode_ordinary(text)


def test_token_counts_equal_library(spark):
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    with open(P.path("word_bpe_49k.json"), encoding="utf-8") as f:
        definition = f.read()
    got = {r.doc_id: r for r in token_counts.count_tokens(edge_cases.frame(spark), definition).collect()}
    for doc_id, text, *_ in edge_cases.rows():
        n = len(lib.encode(text or "", add_special_tokens=False))
        assert (got[doc_id].n_tokens, got[doc_id].n_bytes, got[doc_id].over_limit) == (n, len((text or "").encode()), n > 2048)
    assert token_counts.count_tokens(edge_cases.empty(spark), definition).count() == 0
