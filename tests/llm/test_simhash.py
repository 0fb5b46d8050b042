import itertools
import random

import numpy as np
import xxhash

from erasureml.llm import simhash


def brute(rows):
    out, prints = {}, {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sh = [b" ".join(w[k : k + 4]) for k in range(max(1, len(w) - 3))] if w else []
        h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
        prints[i] = sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))
    parent = {i: i for i in prints}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(prints), 2):
        if bin(prints[a] ^ prints[b]).count("1") <= 4:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    for i in prints:
        out[i] = (f"{prints[i]:016x}", find(i))
    return out


def texts():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(400)]
    base = [" ".join(rng.choices(words, k=rng.choice([3, 40, 200]))) for _ in range(60)]
    rows = [None, "", " \n", "One", "one  ONE", *base]
    for t in base[:20]:
        for _ in range(4):
            w = t.split()
            w[rng.randrange(len(w))] = rng.choice(words)
            rows.append(" ".join(w))
    return list(enumerate(rows + base[:5] * 3))


def test_components_against_all_pairs(spark, tmp_path):
    rows = texts()
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.op6_simhash(spark, str(tmp_path)).collect()}
    assert got == brute(rows)


def test_blocks_split_a_large_bucket(spark):
    rng = np.random.default_rng(0)
    f = [int(np.bitwise_xor.reduce(np.int64(1) << rng.choice(60, 3, replace=False))) for _ in range(80)]
    keys = spark.createDataFrame([(0, 0, i) for i in range(80)], "t int, key long, node long")
    prints = spark.createDataFrame([(i, [x]) for i, x in enumerate(f)], "node long, f array<long>")
    roots = [{r.node: r.root for r in simhash.components(simhash.links(keys, prints, 4, block)).collect()} for block in (7, 4096)]
    assert roots[0] == roots[1] and len(roots[0]) > 40


def test_masks_cover_every_small_difference():
    masks = simhash.covering_masks(4)
    rng = random.Random(1)
    for _ in range(20000):
        d = sum(1 << i for i in rng.sample(range(64), 4))
        assert any(not d & m for m in masks)
    assert all(24 <= bin(m).count("1") <= 40 for m in masks)


def test_near_groups_by_similarity(spark):
    rng = random.Random(9)
    words = [f"v{i}" for i in range(3000)]
    base = [rng.choices(words, k=300) for _ in range(40)]
    rows, k = [], 0
    for b in base:
        near = list(b)
        for at in rng.sample(range(300), 4):
            near[at] = "edited"
        far = list(b)
        for at in rng.sample(range(300), 60):
            far[at] = rng.choice(words)
        for t in (b, near, far):
            rows.append((k, " ".join(t)))
            k += 1
    got = {r.doc_id: r.component_id for r in simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[i + 1] == i for i in range(0, k, 3))
    assert all(got[i + 2] == i + 2 for i in range(0, k, 3))


def test_empty_and_null_ids(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert simhash.near_groups(none).collect() == []
    some = spark.createDataFrame([(None, "a b c"), (3, "a b c"), (3, "a b c"), (4, None)], "doc_id long, text string")
    assert sorted((r.doc_id or -1, r.component_id) for r in simhash.near_groups(some).collect()) == [(-1, None), (3, 3), (3, 3), (4, 4)]


def shingled(text, size=5):
    w = text.split()
    return {" ".join(w[k : k + size]) for k in range(max(1, len(w) - size + 1))}


def jaccard_roots(rows, similarity=0.8):
    """All pairs of (id, text): the smallest id that each one is connected with."""
    sets, parent = {i: shingled(t) for i, t in rows}, {i: i for i, _ in rows}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both >= similarity * (len(sets[a]) + len(sets[b]) - both):
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    return {i: find(i) for i in sets}


def crowd(copies, seed=3):
    """A text and copies of it at 0.67 to 0.85, each with a twin that differs from it by a word."""
    rng = random.Random(seed)
    base = [f"b{i}" for i in range(300)]
    rows = [" ".join(base)]
    for k in range(copies // 2):
        w = list(base)
        for at in rng.sample(range(300), rng.randint(5, 11)):
            w[at] = f"e{k}x{at}"
        twin = list(w)
        twin[rng.randrange(300)] = f"t{k}"
        rows += [" ".join(w), " ".join(twin)]
    return list(enumerate(rows))


def cut_crowd(texts=20, copies=60):
    """Copies of short texts with another last word, and two texts without the first 2 and 4 words: the second is alike to
    the first (12 of 14 shingles) but to no copy (0.65 to 0.75), and all shingles of it are in a crowd."""
    rows = []
    for k in range(texts):
        base = [f"c{k}w{i}" for i in range(20)]
        rows += [" ".join(base), " ".join(base[2:]), " ".join(base[4:]), *(" ".join(base[:-1] + [f"e{i}"]) for i in range(copies))]
    return list(enumerate(rows))


def test_forest_against_all_pairs():
    rows = crowd(300)
    sets = [np.unique(simhash.shingle_hashes(t, 5)) for _, t in rows]
    parent = {i: i for i, _ in rows}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    got = simhash.forest(sets, np.arange(len(rows)), 0.8)
    for a, b in got:
        x, y = sorted((find(a), find(b)))
        assert x != y
        parent[y] = x
    want = jaccard_roots(rows)
    assert {i: find(i) for i in parent} == want and 20 < len(set(want.values())) < 140


def test_crowded_group_against_all_pairs(spark):
    rows = crowd(400)
    rows += [(len(rows) + i, t) for i, t in cut_crowd()]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = jaccard_roots(rows)
    assert {r.doc_id: r.component_id for r in simhash.near_groups(docs).collect()} == want
    keys = spark.createDataFrame([(t, 0, i) for t in (0, 1) for i, _ in rows], "t int, key long, node long")
    for block, hashes in ((4096, 1 << 21), (60, 1 << 21), (4096, 20000)):
        roots = {r.node: r.root for r in simhash.components(simhash.crowded(keys, docs, 5, 0.8, block, hashes)).collect()}
        assert all(roots.get(i, i) == want[i] for i in want)


def test_repeats_and_short_texts_against_all_pairs(spark):
    """Sets of shingles decide: how often a line is repeated doesn't count, and short texts differ in many bits."""
    rng, rows = random.Random(4), []
    for k in range(30):
        line, text = (" ".join(f"r{k}x{rng.randrange(10**6)}" for _ in range(n)) for n in (20, 200))
        rows += [f"{text} {line}", " ".join([text, *[line] * 10])]
    for k in range(100):
        w = [f"s{k}x{i}" for i in range(9)]
        rows += [" ".join(w), " ".join(w[:8])]
    rows = list(enumerate(rows))
    got = {r.doc_id: r.component_id for r in simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    want = jaccard_roots(rows)
    assert got == want and all(want[i + 1] == i for i in range(0, len(rows), 2))


def test_rows_of_one_id_share_a_component(spark):
    rng = random.Random(12)
    words = [f"u{i}" for i in range(900)]
    a, b, c = (" ".join(rng.choices(words, k=60)) for _ in range(3))
    rows = [(2, a), (5, a), (5, b), (7, b), (9, c), (9, c), (11, c), (3, ""), (4, None), (None, a)]
    want = {2: 2, 5: 2, 7: 2, 9: 9, 11: 9, 3: 3, 4: 3, None: None}
    docs = spark.createDataFrame([(i, t, k, "x") for k, (i, t) in enumerate(rows)], "doc_id long, text string, n int, component_id string")
    for found in (simhash.near_groups(docs), simhash.grouped(simhash.fingerprints(docs))):
        assert {r.doc_id: r.component_id for r in found.collect()} == want and found.count() == len(rows)
    kept = simhash.stage(spark, docs, "")
    assert kept.columns == docs.columns and sorted(r.n for r in kept.collect()) == [0, 4, 5, 7, 9]


def test_a_very_long_text_and_its_edit(spark):
    rng = random.Random(13)
    words = [rng.choice("abcdefgh") + str(rng.randrange(10**6)) for _ in range(120000)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join([*words[:-50], "end"])), (3, " ".join(words[:40000]))], "doc_id long, text string")
    assert {r.doc_id: r.component_id for r in simhash.near_groups(docs).collect()} == {1: 1, 2: 1, 3: 3}
