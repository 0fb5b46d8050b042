import random

import public_tokenizers
import tiktoken  # noqa: F401
from tokenizers import Tokenizer

import corpus_pipeline
from erasureml.llm import bpe, containment, pii, simhash, toxicity


def test_stages_on_their_own_input(spark):
    at, docs = "/root/testdata/sf0.001", None
    docs = spark.read.parquet(f"{at}/documents.parquet")
    columns = docs.columns
    kept = [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        kept.append(stage(spark, kept[-1], at).cache())
        assert kept[-1].columns == columns
    texts = [{r.doc_id: r.text for r in k.collect()} for k in kept]
    # toxicity: what the fitted model rejects, and nothing else
    model = toxicity.fit(docs, spark.read.parquet(f"{at}/labels.parquet"))
    assert texts[1] == {i: t for i, t in texts[0].items() if model.above(t)[0] < model.cut}
    # near copies: no two that remain are alike, and every one that went has a partner in its group
    groups = {r.doc_id: r.component_id for r in simhash.near_groups(kept[1]).collect()}
    assert texts[2].keys() == {i for i, g in groups.items() if i == g}
    # decontamination against brute force
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{at}/benchmark.parquet").collect()]
    dirty = set()
    for _, t in items:
        own = containment.shingles(t, min(5, len(containment._WORD.findall(t.lower()))))
        dirty |= {i for i, x in texts[2].items() if own and len(own & containment.shingles(x, len(next(iter(own))))) >= 0.8 * len(own) - 1e-9}
    assert texts[3].keys() == texts[2].keys() - dirty and dirty
    # redaction
    assert texts[4].keys() == texts[3].keys()
    assert sum(t != texts[3][i] for i, t in texts[4].items()) > 0
    assert not any("@mail" in t for t in texts[4].values())
    # tokens
    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    tok.encode_special_tokens = True
    for r in bpe.stage(spark, kept[-1], at).collect():
        assert r.ids == tok.encode(texts[4][r.doc_id], add_special_tokens=False).ids
    ran = {r.doc_id for r in corpus_pipeline.run(spark, at).select("doc_id").collect()}
    assert ran == texts[4].keys()


def test_exact_copies_leave_one(spark):
    rng = random.Random(1)
    words = [f"k{i}" for i in range(500)]
    base = [" ".join(rng.choices(words, k=80)) for _ in range(30)]
    docs = spark.createDataFrame([(i, base[i % 30], f"x{i}") for i in range(90)] + [(None, base[0], "y")], "doc_id long, text string, fingerprint string")
    got = sorted((r.doc_id is None, r.doc_id or 0, r.fingerprint) for r in simhash.stage(spark, docs, "").collect())
    assert got == [(False, i, f"x{i}") for i in range(30)] + [(True, 0, "y")]


def test_stages_take_an_empty_table(spark):
    at = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{at}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, at).collect() == []
    assert pii.KINDS
