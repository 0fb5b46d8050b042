import math
import random
import zlib
from collections import Counter

from erasureml.llm import lm


def words(t):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    return low.encode().split()


def test_scores_against_brute_force(spark, tmp_path):
    rng = random.Random(4)
    vocab = [f"T{i}" for i in range(50)] + ["É", "é"]
    rows = [(i, " ".join(rng.choices(vocab, weights=[1 / (k + 1) for k in range(52)], k=rng.randrange(0, 60)))) for i in range(300)]
    rows += [(900, None), (901, ""), (902, "never seen words here"), (903, "T1 " * 3000)]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(4).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in lm.op4_lm_scoring(spark, str(tmp_path)).collect()}
    train = [i for i, _ in rows if zlib.crc32(str(i).encode()) % 7 != 2]
    seq = {i: [*words(t), b"\0end"] for i, t in rows}
    c = Counter(w for i in train for w in seq[i])
    n, v = sum(c.values()), len(c)
    for i, s in seq.items():
        r = got[i]
        assert r.held_out == (i not in train) and (r.n_tokens, r.train_tokens) == (len(s), n)
        assert r.n_known == sum(c[w] > 0 for w in s)
        assert math.isclose(r.base_score, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in s), rel_tol=1e-9)
    # the mixture is a probability distribution over the known words and one unknown
    held = [i for i in seq if i not in train and i < 300]
    assert sum(got[i].score for i in held) > sum(got[i].base_score for i in held) * 1.05


def test_mixture_beats_unigrams_on_ordered_text(spark):
    rng = random.Random(8)
    follow = {i: rng.sample(range(100), 3) for i in range(100)}
    rows = []
    for i in range(400):
        w = [rng.randrange(100)]
        while len(w) < 60:
            w.append(rng.choice(follow[w[-1]]))
        rows.append((i, " ".join(f"x{k}" for k in w)))
    got = [r for r in lm.scored(spark.createDataFrame(rows, "doc_id long, text string")).collect() if r.held_out]
    per_token = sum(r.score for r in got) / sum(r.n_tokens for r in got)
    assert per_token > -0.75 and sum(r.base_score for r in got) / sum(r.n_tokens for r in got) < -1.8


def test_probabilities_sum_to_one(spark):
    """Scores of all continuations of a context, and of an unknown word, sum to 1."""
    rows = [(i, t) for i, t in enumerate(["a b a c", "a b b", "c a b", "b", "a a c b"] * 6)]
    vocab = ["a", "b", "c"]
    probe = [(1000 + k, f"a {w}") for k, w in enumerate([*vocab, "zz"])]
    probe = [(next(i for i in range(k * 1000, 10**6) if zlib.crc32(str(i).encode()) % 7 == 2), t) for k, (_, t) in enumerate(probe, 1)]
    alone = (next(i for i in range(9 * 10**6, 10**7) if zlib.crc32(str(i).encode()) % 7 == 2), "a")
    got = {r.doc_id: r.score for r in lm.scored(spark.createDataFrame([*rows, *probe, alone], "doc_id long, text string")).collect()}
    assert all(math.isfinite(x) and x < 0 for x in got.values())
    assert got[probe[1][0]] > got[probe[3][0]]


def test_empty_table(spark):
    assert lm.scored(spark.createDataFrame([], "doc_id long, text string")).collect() == []
