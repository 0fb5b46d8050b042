import base64
import hashlib
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from erasureml.llm import bpe, tokens

ODD = [None, "a  b   c\n d\n\n  e \t f\r\n", " lead", "trail  ", "\n", "x\ty ÷ z× É à!", "12ab34 $$$ a.b,c", "  ", "a \nb", "", " ", "a", "  two  spaces \n\n\tend  ", "don't we'll it's", "日本語 héllo wörld 😀😀 é", "<|endoftext|> x <|startoftext|>", "\x1c a\x1cb \x85 c\xa0d e", "x" * 5000, "12 345 6789 !!! ?", "É" * 50 + " " * 40, "word " * 60000, "á ́b ΑΣ σ"]


@given(st.lists(st.integers(0, 2**64 - 1) | st.integers(0, 3) | st.integers(0, 50000), max_size=300))
@settings(max_examples=150, deadline=None)
def test_simple8b_round_trip(values):
    v = np.array(values, np.uint64)
    assert (tokens.s8b_decode(tokens.s8b_encode(v), len(v)) == v).all()


def test_simple8b_density():
    assert len(tokens.s8b_encode(np.zeros(600, np.uint64))) == 10
    assert len(tokens.s8b_encode(np.full(400, 30000, np.uint64))) == 100


@pytest.fixture(scope="module")
def texts(spark):
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()
    return [(r.doc_id + 100, r.text) for r in rows] + list(enumerate(ODD))


def test_store_against_the_library(spark, texts, tmp_path):
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    path = f"{tmp_path}/store"
    tokens.write_store(docs, path, tokens.default_vocabulary(), block_ids=2000)
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    at = 0
    got = {r.doc_id: r for r in tokens.checksums(spark, path).collect()}
    full = {r.doc_id: r.ids for r in tokens.read_store(spark, path).collect()}
    for i, t in sorted(texts):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes())), (i, t)
        assert full[i] == ids.tobytes()
        at += len(ids)


def test_byte_bpe_against_tiktoken(spark, texts):
    with open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    path = bpe.default_vocabulary()
    got = {r.doc_id: r for r in bpe.round_trip(docs, path).collect()}
    coded = {r.doc_id: r for r in bpe.encode(docs, path, offsets=True).collect()}
    for i, t in texts:
        ids = enc.encode_ordinary(t or "")
        assert (got[i].n_tokens, got[i].ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()), (i, t)
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
        assert coded[i].ids == ids and bpe.decode(np.array(ids), path) == (t or "")
        assert "".join(bpe.pieces(np.array(ids), path)) == (t or "")
        assert len(ids) >= 2000 or coded[i].starts == enc.decode_with_offsets(ids)[1]


def test_empty_tables(spark, tmp_path):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert bpe.round_trip(none, bpe.default_vocabulary()).collect() == []
    tokens.write_store(none, f"{tmp_path}/s", tokens.default_vocabulary())
    assert tokens.checksums(spark, f"{tmp_path}/s").collect() == []
