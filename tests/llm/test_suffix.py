import hashlib
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from erasureml.llm import suffix


@given(st.binary(max_size=80) | st.text("ab", max_size=120).map(str.encode), st.integers(0, 2**31))
@settings(max_examples=200, deadline=None)
def test_suffix_order(text, seed):
    wanted = np.random.default_rng(seed).random(len(text)) < 0.7
    got = suffix.suffix_order(text, wanted, len(text) + 1).tolist()
    assert got == sorted(np.flatnonzero(wanted).tolist(), key=lambda i: text[i:])


def brute(rows, length=200):
    seen = {}
    data = [(t or "").encode() for _, t in rows]
    for d, b in enumerate(data):
        for i in range(len(b) - length + 1):
            seen.setdefault(b[i : i + length], []).append((d, i))
    gone = [np.zeros(len(b), bool) for b in data]
    for at in seen.values():
        if len(at) > 1:
            for d, i in at:
                gone[d][i : i + length] = True
    out = []
    for (i, _), b, g in zip(rows, data, gone, strict=True):
        spans = int((g & ~np.concatenate([[False], g[:-1]])).sum()) if len(g) else 0
        out.append((i, len(b), int(g.sum()), spans, hashlib.sha256(np.frombuffer(b, np.uint8)[~g].tobytes()).hexdigest()))
    return out


def texts():
    rng = random.Random(1)
    words = ["alpha", "beta", "é", "gamma,", "x", "日本"]
    noise = lambda k: " ".join("".join(rng.choices("abcdefghij", k=rng.randrange(2, 9))) for _ in range(k))
    shared = [noise(k) for k in (15, 25, 35, 40, 41, 60, 200)]
    out = [None, "", "a" * 1000, "ab" * 400, " ".join(rng.choices(words, k=900))]
    for _ in range(60):
        out.append(noise(rng.randrange(0, 60)) + "".join(rng.choice(shared) + noise(rng.randrange(3)) for _ in range(rng.randrange(3))))
    return out + out[10:16] + [noise(10) + out[2][:450]]


@pytest.mark.parametrize("hot", [256, 4, 0])
def test_removed_bytes_against_brute_force(spark, hot):
    rows = list(enumerate(texts() + [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").orderBy("doc_id").limit(60).collect()]))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    frame = suffix.each_block(suffix.matched(docs, hot), lambda b: suffix._rows(b, lambda k: hashlib.sha256(k).hexdigest(), "kept_sha256"), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    got = sorted(tuple(r) for r in frame.collect())
    want = brute(rows)
    assert [g for g, w in zip(got, want, strict=True) if g != w] == []
    assert sum(w[2] for w in want) > 20000


def test_long_text_is_cut_into_segments(spark, monkeypatch):
    monkeypatch.setattr(suffix, "SEGMENT", 1 << 12)
    rng = random.Random(3)
    noise = lambda n: "".join(rng.choices("abcdefghijklmnop ", k=n))
    shared = noise(9000)
    rows = [(1, noise(20000) + shared + noise(500)), (2, noise(1234) + shared), (3, noise(100))]
    block = type("Row", (), {"lens": np.array([len(t) for _, t in rows]).tobytes(), "doc_ids": np.array([1, 2, 3]).tobytes(), "block_id": 0, "body": suffix.squeeze("".join(t for _, t in rows).encode())})
    first, count, h = suffix.anchors(suffix.Block(block))
    assert count.sum() == sum(max(0, len(t) - 199) for _, t in rows)
    monkeypatch.setattr(suffix, "SEGMENT", 1 << 20)
    a, n, g = suffix.anchors(suffix.Block(block))
    assert dict.fromkeys(zip(np.repeat(h, count), strict=True)) == dict.fromkeys(zip(np.repeat(g, n), strict=True))


def test_empty_table_and_equal_ids(spark):
    assert suffix.deduplicated(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    got = [(r.doc_id, r.n_removed) for r in suffix.deduplicated(spark.createDataFrame([(7, "q" * 100 + "r" * 150), (7, "q" * 100 + "r" * 150), (None, "s" * 150)], "doc_id long, text string")).collect()]
    assert sorted(got, key=str) == [(7, 250), (7, 250), (None, 0)]
