"""Language-model scoring by deleted interpolation.

Tokens are words in lower case (A-Z) and one end a document.  A bigram's, a unigram's and a uniform estimate are mixed:

    p(w | v) = a2(b) c(v w)/c(v) + a1(b) c(w)/N + a0(b) / (V + 1)

with weights for every bucket b of contexts of like frequency (powers of two).  Documents with
crc32(doc_id) mod 7 = 2 are held out.  The weights are learned by expectation-maximisation on the counts of one fold of the
training documents (crc32 mod 7 = 3) under estimates from which that fold's own counts are deleted.  EM needs
only, for each bucket, how often which pair of ratios to the uniform estimate occurs: a histogram on a grid of a quarter
octave, whose size doesn't depend on the corpus.  Scores use all training counts, exactly.

The end stands as the context of a document's first word.  Counts of all n-grams of a block are asked from the
corpus in one go (core.answers).  A word is identified by 96 bits of two independent hashes; a bigram by 64 bits of
its words' hashes, so of 10^12 different bigrams some 30,000 would share counts, which moves only those bigrams' share in
`score`.  Null and empty texts are the end only; a null doc_id counts as training.  Repeated rows are documents of their
own, each counted and scored.  Only doc_id and text are read; no other column is returned.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import NO_ID, Block, Words, answer_of, answers, attach, distinct, each_block, mix, read_table, run_of, spread, tally_of, text_blocks

HELD_OUT, FOLD, FOLDS = 2, 3, 7
END = np.uint64(0x5EED0FE4D)
BUCKETS = 48
GRID = 4
START = (0.2, 0.6, 0.2)


def fold_of(ids: np.ndarray) -> np.ndarray:
    return np.array([zlib.crc32(str(i).encode()) % FOLDS if i != NO_ID else 0 for i in ids.tolist()], np.int64)


class Scan:
    """All tokens of a block with ends, their contexts and rows."""

    def __init__(self, block: Block) -> None:
        hashes, checks, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for i, j in block.chunks():
            words = Words(block, i, j, lower=True)
            hashes.append(words.hash), checks.append(words.check >> np.uint64(32)), counts.append(words.counts)
        counts = np.concatenate(counts)
        self.word = np.insert(np.concatenate(hashes), np.cumsum(counts), END)
        self.check = np.insert(np.concatenate(checks), np.cumsum(counts), END)
        self.counts = counts + 1
        self.row = np.repeat(np.arange(len(self.counts)), self.counts)
        self.context = np.concatenate([[END], self.word[:-1]]) if len(self.word) else self.word
        self.fold = fold_of(block.doc_ids)
        with np.errstate(over="ignore"):
            self.pair = mix(self.word + mix(self.context ^ END) * np.uint64(0xD6E8FEB86659FD93))

    def asks(self, hashes: np.ndarray, check: np.ndarray | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
        keys, order, at = distinct(hashes, check)
        fold = self.fold[self.row][order]
        sums = [np.add.reduceat((fold != HELD_OUT).astype(np.int64), at), np.add.reduceat((fold == FOLD).astype(np.int64), at)] if len(at) else [np.zeros(0, np.int64)] * 2
        return keys, sums if check is None else [check[order[at]], *sums]


def totals(values: list[np.ndarray], at: np.ndarray) -> list[np.ndarray]:
    """Training counts, and the fold's where the block has a part in it: only there are they used."""
    train, fold = (spread(np.add.reduceat(v, at), at, len(v)) for v in values)
    return [train, np.where(values[1] > 0, fold, 0)]


def tally(values: list[np.ndarray], at: np.ndarray) -> list[int]:
    """Training types, training tokens and the fold's tokens."""
    return [int((np.add.reduceat(values[0], at) > 0).sum()), int(values[0].sum()), int(values[1].sum())]


class Counts:
    """What a block's bigrams and words count in the corpus."""

    def __init__(self, block: Block) -> None:
        self.scan = scan = Scan(block)
        _, order, at = distinct(scan.word, scan.check)
        self.of_word = run_of(order, at)
        # the context is the word before; the first one's is the end, as which the block ends
        context = np.concatenate([self.of_word[-1:], self.of_word[:-1]])
        _, order, at = distinct(scan.pair)
        first = order[at]
        self.of_pair = run_of(order, at)
        c, f = (answer_of(block.row, "one", k) for k in (0, 1))
        self.word, self.word_fold = c, f
        w, v = self.of_word[first], context[first]
        self.w, self.w_fold, self.v, self.v_fold = c[w], f[w], c[v], f[v]
        self.c, self.c_fold = (answer_of(block.row, "two", k) for k in (0, 1))
        fold = (scan.fold[scan.row] == FOLD)[order]
        self.own_fold = np.add.reduceat(fold.astype(np.int64), at) if len(at) else np.zeros(0, np.int64)


def bucket_of(n: np.ndarray) -> np.ndarray:
    return np.minimum(np.floor(np.log2(n + 1)).astype(np.int64), BUCKETS - 1)


def histogram(types: int, tokens: int, fold: int):
    """work for each_block: (bucket, q2, q1, n); q: log2 of the estimate over the uniform one on the grid, or null for 0."""

    def work(block: Block) -> Iterator[pd.DataFrame]:
        x = Counts(block)
        use = x.own_fold > 0
        v, c, w = ((a - b)[use] for a, b in ((x.v, x.v_fold), (x.c, x.c_fold), (x.w, x.w_fold)))
        with np.errstate(divide="ignore", invalid="ignore"):
            q2 = np.where(c > 0, np.round(GRID * np.log2(c / np.maximum(v, 1) * (types + 1))), -9999)
            q1 = np.where(w > 0, np.round(GRID * np.log2(w / max(tokens - fold, 1) * (types + 1))), -9999)
        frame = pd.DataFrame({"bucket": bucket_of(v), "q2": q2.astype(np.int64), "q1": q1.astype(np.int64), "n": x.own_fold[use]})
        yield frame.groupby(["bucket", "q2", "q1"], as_index=False).sum()

    return work


def learn(table: pd.DataFrame, rounds: int = 60) -> np.ndarray:
    """Weights (bucket, [a2, a1, a0]) by EM on the histogram."""
    weights = np.tile(np.array(START), (BUCKETS, 1))
    for b, own in table.groupby("bucket"):
        ratio = np.stack([np.where(own[q] > -9999, np.exp2(own[q] / GRID), 0.0) for q in ("q2", "q1")] + [np.ones(len(own))], 1)
        n, a = own["n"].to_numpy(float), np.array(START)
        for _ in range(rounds):
            part = ratio * a
            a = (part / part.sum(1, keepdims=True) * n[:, None]).sum(0) / n.sum()
            a = np.maximum(a, 1e-6) / np.maximum(a, 1e-6).sum()
        weights[int(b)] = a
    return weights


def scores(types: int, tokens: int, weights: np.ndarray):
    def work(block: Block) -> Iterator[pd.DataFrame]:
        x = Counts(block)
        ends = np.cumsum(x.scan.counts)
        a = weights[bucket_of(x.v)]
        free = a[:, 1] + a[:, 2]
        # a context never seen in training has no bigram estimate: the others take its weight
        a2, scale = np.where(x.v > 0, a[:, 0], 0), np.where(x.v > 0, 1, 1 / free)
        p = a2 * x.c / np.maximum(x.v, 1) + scale * (a[:, 1] * x.w / max(tokens, 1) * (tokens > 0) + a[:, 2] / (types + 1))
        known = x.word[x.of_word]
        base = np.log10((known + 1) / (tokens + types + 1))

        def by_row(values: np.ndarray) -> np.ndarray:
            return np.add.reduceat(values, ends - x.scan.counts)

        yield pd.DataFrame(
            {
                "doc_id": block.ids_out(),
                "held_out": x.scan.fold == HELD_OUT,
                "n_tokens": x.scan.counts,
                "n_known": by_row((known > 0).astype(np.int64)),
                "train_tokens": np.full(len(ends), tokens, np.int64),
                "base_score": by_row(base),
                "score": by_row(np.log10(p)[x.of_pair]),
            }
        )

    return work


def scored(docs: DataFrame) -> DataFrame:
    blocks = text_blocks(docs)
    one = answers(blocks, lambda b: (s := Scan(b)).asks(s.word, s.check), totals, tally, wide=True)
    two = answers(blocks, lambda b: (s := Scan(b)).asks(s.pair), totals)
    types, tokens, fold = tally_of(one, 3)
    counted = attach(attach(blocks, one, "one"), two, "two")
    table = each_block(counted, histogram(types, tokens, fold), "bucket long, q2 long, q1 long, n long")
    weights = learn(table.groupBy("bucket", "q2", "q1").agg(F.sum("n").alias("n")).orderBy("bucket", "q2", "q1").toPandas())
    return each_block(counted, scores(types, tokens, weights), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(read_table(spark, sf_dir, "documents"))
