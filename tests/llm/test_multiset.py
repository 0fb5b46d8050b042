import hashlib
import random

import numpy as np

from erasureml.llm import multiset


def test_order_insertion_and_deletion():
    a, b, c = multiset.vectors(["one two three four", "five six\n\nseven", "x"])
    whole, turned = multiset.vectors(["one two three four\nfive six\n\nseven\nx", "x\nfive six\n\nseven\none two three four"])
    assert (whole == turned).all()
    ends = multiset.subtract(multiset.vectors(["x\n"])[0], c)
    assert (multiset.add(multiset.add(multiset.add(a, b), c), multiset.add(ends, ends)) == whole).all()
    assert (multiset.subtract(multiset.add(a, b), a) == b).all()
    assert not multiset.vectors([None, ""]).any()
    assert len({v.tobytes() for v in multiset.vectors(["a", "a\n", "a\na", "A", "a ", "b"])}) == 6


def test_likeness_follows_shared_text():
    rng = random.Random(0)
    for n in (20, 300, 20000):
        words = [str(rng.random()) for _ in range(2 * n)]
        base, half, other = words[:n], words[: n // 2] + words[n : n + n // 2], words[n:]
        v = multiset.vectors([" ".join(x) for x in (base, half, other)])
        near, far = multiset.likeness(v[[0, 0]], v[[1, 2]])
        assert 0.12 < near < 0.65 and far < 0.1, (n, near, far)


def test_digest_against_brute_force(spark, tmp_path):
    rng = random.Random(2)
    rows = [(rng.randrange(10**9) if i % 2 else i, "\n".join(" ".join(rng.choices("abcdé", k=5)) for _ in range(rng.randrange(0, 9)))) for i in range(200)]
    rows = list({i: (i, t) for i, t in rows}.values()) + [(-5, None), (2 * 10**9, "")]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(5).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in multiset.op5_fingerprint(spark, str(tmp_path)).collect()}
    order = sorted((i, t or "") for i, t in rows)
    assert len(got) == len(order)
    for k, (i, t) in enumerate(order):
        after = order[(k + 1) % len(order)][1]
        new = multiset.edited(t, after)
        v = multiset.vectors([t, new, after])
        r = got[i]
        assert (r.n_chars, r.edited_sha256, r.fingerprint, r.edited_fingerprint) == (len(t), hashlib.sha256(new.encode()).hexdigest(), v[0].tobytes().hex(), v[1].tobytes().hex())
        assert [r.near_edited, r.near_next] == multiset.likeness(v[[0, 0]], v[1:]).tolist()


def test_updates_and_odd_tables(spark):
    docs = spark.createDataFrame([(1, "a b c\nd e f"), (2, "q"), (None, "r")], "doc_id long, text string")
    changes = spark.createDataFrame([(1, "d e f", False), (1, "new words here", True)], "doc_id long, paragraph string, inserted boolean")
    got = {r.doc_id: r.fingerprint for r in multiset.updated(multiset.fingerprints(docs), changes).collect()}
    want = multiset.vectors(["a b c\nnew words here", "q", "r"])
    assert [bytes(got[k]) for k in (1, 2, None)] == [v.tobytes() for v in want]
    assert multiset.digest(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    one = multiset.digest(spark.createDataFrame([(None, "solo text")], "doc_id long, text string")).collect()
    assert [(r.doc_id, r.near_next) for r in one] == [(None, 1.0)]
    twice = multiset.digest(spark.createDataFrame([(3, "b"), (3, "a"), (4, "c")], "doc_id long, text string")).collect()
    assert len(twice) == 3 and np.isfinite([r.near_edited for r in twice]).all()
