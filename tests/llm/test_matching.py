import hashlib
import random

import duckdb
import pytest

from erasureml.llm import containment, substring


def passages(n=120, seed=3):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(60)] + ["é", "x.", "Y,"]
    shared = [" ".join(rng.choices(words, k=k)) for k in (5, 12, 13, 14, 30, 60)]
    out = [None, "", "one two"]
    for _ in range(n):
        parts = [" ".join(rng.choices(words, k=rng.randrange(0, 40)))]
        for _ in range(rng.randrange(3)):
            parts += [rng.choice(shared), " ".join(rng.choices(words, k=rng.randrange(0, 8)))]
        out.append(rng.choice([" ", "\n", "  \t"]).join(parts))
    out += out[5:15] + ["Re " * 300]
    return out


def brute_substring(rows):
    first, words = {}, {}
    for i, t in rows:
        words[i] = (t or "").encode().split()
        for k in range(len(words[i]) - 12):
            w = tuple(words[i][k : k + 13])
            first[w] = min(first.get(w, i), i)
    out = {}
    for i, w in words.items():
        gone = set()
        for k in range(len(w) - 12):
            if first[tuple(w[k : k + 13])] < i:
                gone.update(range(k, k + 13))
        out[i] = (len(w), len(gone), hashlib.sha256(b" ".join(x for k, x in enumerate(w) if k not in gone)).hexdigest())
    return out


def test_substring_against_brute_force(spark, tmp_path):
    texts = passages() + [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").orderBy("doc_id").collect()]
    rows = list(enumerate(texts))
    random.Random(0).shuffle(rows)
    spark.createDataFrame(rows, "doc_id long, text string").repartition(6).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring.op9_substring(spark, str(tmp_path)).collect()}
    want = brute_substring(rows)
    assert {k for k in want if got[k] != want[k]} == set()
    assert sum(w[1] for w in want.values()) > 1000


def test_substring_odd_tables(spark):
    assert substring.deduplicated(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    p = " ".join(f"a{i}" for i in range(20))
    got = sorted(((r.doc_id is None, r.doc_id, r.text) for r in substring.deduplicated(spark.createDataFrame([(1, p), (1, p), (2, f"b {p} c"), (None, "x")], "doc_id long, text string")).collect()), key=str)
    assert got == sorted([(False, 1, p), (False, 1, p), (False, 2, "b c"), (True, None, "x")], key=str)


def brute_containment(docs, items):
    out = set()
    for item, text in items:
        n = min(5, len(containment._WORD.findall((text or "").lower())))
        own = containment.shingles(text, n) if n else set()
        for i, t in docs:
            shared = len(own & containment.shingles(t, n)) if n else 0
            if own and shared >= 0.8 * len(own) - 1e-9:
                out.add((i, item, len(own), shared))
    return out


@pytest.mark.parametrize("limit", [1 << 20, 0])
def test_containment_against_brute_force(spark, limit):
    rng = random.Random(2)
    words = [f"q{i}" for i in range(200)]
    items = [(i, " ".join(rng.choices(words, k=rng.randrange(1, 60)))) for i in range(30)] + [(30, None), (31, "?!"), (32, "UNO, dos tres")]
    docs = [(0, None), (1, ""), (2, "dos uno DOS Tres"), (3, "x. UNO dos-tres")]
    for k in range(80):
        t = rng.choice(items[:30])[1].split()
        for _ in range(rng.randrange(3)):
            t[rng.randrange(len(t))] = "zz"
        docs.append((4 + k, " ".join(rng.choices(words, k=rng.randrange(300)) + t + ["END"] + rng.choices(words, k=20)).title()))
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id, r.n_item, r.n_shared) for r in containment.pairs(d, b, index_bytes=limit).collect()}
    assert got == brute_containment(docs, items) and len(got) > 40


def test_containment_against_sql(spark):
    at = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet'")
    want = con.execute(containment.ORACLE).fetchall()
    got = [tuple(r) for r in containment.op8_decontamination(spark, at).collect()]
    assert sorted(got) == sorted(want)


ROWS = [(None, "x one two three four five six y", 1), (1, "x ONE two, three four five six y", 2), (1, "clean", 3), (2, "clean too", 4), (2, "clean too", 5), (None, None, 6), (3, "", 7), (4, "w " * 90000 + "one two three four five six", 8)]


@pytest.mark.parametrize("limit", [1 << 20, 0])
def test_rows_without_or_with_equal_ids_are_told_apart(spark, limit):
    docs = spark.createDataFrame([(i, t, n, "c", "d") for i, t, n in ROWS], "doc_id long, text string, item_id int, h string, _items string")
    items = spark.createDataFrame([(7, "one two three four five six", 0), (7, "w w w w w w", 0), (None, "one two three four five six", 0), (8, None, 0)], "item_id long, text string, text2 int")
    kept = containment.uncontaminated(docs, items, limit)
    assert kept.columns == docs.columns and sorted(r.item_id for r in kept.collect()) == [3, 4, 5, 6, 7]
    got = sorted((str(r.doc_id), str(r.item_id), r.n_item, r.n_shared) for r in containment.pairs(docs, items, index_bytes=limit).collect())
    assert got == sorted([(d, i, 2, 2) for d in ("None", "1", "4") for i in ("7", "None")] + [("4", "7", 1, 1)])
    assert containment.uncontaminated(docs.limit(0), items, limit).collect() == []
    assert containment.uncontaminated(docs, items.limit(0), limit).count() == len(ROWS)
