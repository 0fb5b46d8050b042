"""Texts of doubling patterns, which share the value of any polynomial hash modulo a power of two, are still told apart."""

import base64
import hashlib
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from tokenizers import Tokenizer

from erasureml.llm import bpe, core, lm, multiset, substring, suffix, tokens
from test_lm import words as lm_words
from test_matching import brute_substring
from test_suffix import brute

SIZES = (1024, 2048, 4096, 8192)


def doubled(n: int, a: str, b: str) -> tuple[str, str]:
    one, two = a, b
    while len(one) < n:
        one, two = one + two, two + one
    return one, two


def pairs(a: str = "a", b: str = "b") -> list[str]:
    return [w for n in SIZES for w in doubled(n, a, b)]


def table(spark, tmp_path, rows):
    spark.createDataFrame(rows, "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_the_cheap_hash_is_defeated_and_the_wide_one_is_not():
    for a, b in zip(pairs()[::2], pairs()[1::2], strict=True):
        data = np.frombuffer((a + b).encode(), np.uint8)
        lo, hi = np.array([0, len(a)]), np.array([len(a), len(a) + len(b)])
        roller = core.Roller(5)
        assert len(set(roller.ranges(roller.prefix(data), lo, hi).tolist())) == 1
        for h in core.range_hash(data, lo, hi):
            assert len(set(h.tolist())) == 2


@pytest.mark.parametrize("size", range(70))
def test_range_hash_follows_the_bytes(size):
    rng = np.random.default_rng(size)
    data = rng.integers(0, 3, 4000, dtype=np.uint8)
    lo = rng.integers(0, 4000 - size, 300)
    one, two = core.range_hash(data, lo, lo + size)
    seen = [data[i : i + size].tobytes() for i in lo]
    for h in (one, two):
        assert len({(x, y) for x, y in zip(h.tolist(), seen, strict=True)}) == len(set(seen)) == len(set(h.tolist()))


def test_distinct_keeps_strings_apart_that_share_a_hash():
    h, c = np.array([7, 7, 3, 7, 7], np.uint64), np.array([1, 2, 9, 1, 2], np.uint64)
    keys, order, at = core.distinct(h, c)
    assert keys.tolist() == [3, 7, 7] and c[order[at]].tolist() == [9, 1, 2]
    assert core.run_of(order, at).tolist() == [1, 2, 0, 1, 2]


def test_tokens(spark, tmp_path):
    rows = [(i, f"{w} and {w}") for i, w in enumerate([*pairs(), *pairs("é", "ü"), *pairs("1", "2"), "<|endoftext|> x", "y <|startoftext|>"])]
    at = table(spark, tmp_path, rows)
    with open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r.doc_id: r for r in bpe.op10_byte_bpe(spark, at).collect()}
    for i, t in rows:
        assert got[i].ids_sha256 == hashlib.sha256(np.array(enc.encode_ordinary(t), "<u4").tobytes()).hexdigest(), i
        assert got[i].decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()
    plain = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = {r.doc_id: r for r in tokens.op7_token_store(spark, at).collect()}
    for i, t in rows:
        ids = np.array([*plain.encode(t, add_special_tokens=False).ids, 2], "<u4")
        assert (got[i].n_tokens, got[i].ids_crc32) == (len(ids), zlib.crc32(ids.tobytes())), i


def test_pieces_stay_apart_when_the_memo_is_full(monkeypatch):
    import pyarrow as pa

    from erasureml.llm import pieces

    monkeypatch.setattr(pieces, "LONG_BYTES", 3000)
    monkeypatch.setattr(pieces, "MEMO", 3)
    coder = bpe.ByteCoder(bpe.default_vocabulary())
    texts = [f"x {w} y" for w in pairs()]
    for _ in range(2):
        for t in texts:
            ids, _ = coder.encode(pa.array([t, "z" * 40]))
            assert bpe.decode(ids, bpe.default_vocabulary()) == t + "z" * 40


def test_ranks_are_checked(tmp_path):
    lines = open(bpe.default_ranks(), "rb").read().splitlines()
    a, b = lines[300].split()[0], lines[301].split()[0]
    lines[300], lines[301] = b + b" 300", a + b" 301"
    (tmp_path / "r").write_bytes(b"\n".join(lines))
    bpe.check_ranks(bpe.default_vocabulary(), bpe.default_ranks())
    with pytest.raises(ValueError):
        bpe.check_ranks(bpe.default_vocabulary(), str(tmp_path / "r"))


def test_cut_texts_give_the_same_ids():
    import random

    import pyarrow as pa

    rng = random.Random(6)
    marks = ["a", "Bc", " ", "  ", "\n", "1", "23", "'s", "!", "é", "日", "\t", " ", "x" * 9, "?!", "'ll"]
    path = bpe.default_vocabulary()
    for _ in range(300):
        text = "".join(rng.choices(marks, k=rng.randrange(1, 120)))
        whole = [i for e in bpe.tokenizer(path).encode_batch_fast([text], add_special_tokens=False) for i in e.ids]
        cut = [i for p in bpe.parts(text, 20) for i in bpe.tokenizer(path).encode(p, add_special_tokens=False).ids]
        assert cut == whole == np.concatenate(list(bpe.encode_texts(pa.array([text]), path))).tolist(), text


def test_substring(spark, tmp_path):
    frame = [f"w{k}" for k in range(12)]
    rows = [(i, " ".join([*frame[:6], w, *frame[6:]])) for i, w in enumerate(pairs())] + [(100, " ".join([*frame[:6], pairs()[0], *frame[6:]]))]
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring.op9_substring(spark, table(spark, tmp_path, rows)).collect()}
    assert got == brute_substring(rows) and got[100][1] == 13 and got[1][1] == 0


def test_language_model(spark, tmp_path):
    one = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 7 != 2)
    held = [i for i in range(100, 400) if zlib.crc32(str(i).encode()) % 7 == 2]
    rows = [(one, " ".join(pairs()[::2]))] + [(i, w) for i, w in zip(held, pairs(), strict=False)]
    got = {r.doc_id: r for r in lm.op4_lm_scoring(spark, table(spark, tmp_path, rows)).collect()}
    known = set(lm_words(rows[0][1]))
    for i, t in rows[1:]:
        assert got[i].n_known == sum(w in known for w in lm_words(t)) + 1, i


def test_fingerprints():
    v = multiset.vectors(pairs())
    assert len({x.tobytes() for x in v}) == len(v)
    assert (multiset.likeness(v[::2], v[1::2]) < 1).all()
    strong = v[:, : 8 * multiset.STRONG].copy().view(np.uint64)
    a, b = strong[0], strong[1]
    assert all(x != y for x, y in zip(a, b, strict=True))


@pytest.mark.parametrize("hot", [1, 256])
def test_suffixes(spark, hot):
    rows = [(i, w) for i, w in enumerate([*pairs(), pairs()[2] + "c", "q" + pairs()[5][300:900], *doubled(256, "xy", "yx")])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    blocks = suffix.matched(docs, hot)
    import hashlib as hl

    kept = core.each_block(blocks, lambda b: suffix._rows(b, lambda k: hl.sha256(k).hexdigest(), "kept_sha256"), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    assert sorted(tuple(r) for r in kept.collect()) == sorted(brute(rows))
