"""Toxicity severity by cumulative-link ordinal regression on sparse text features.

Grades 0 (clean), 1 (toxic) and 2 (severe) share one weight vector; ordered thresholds part them:
P(grade > k) = logistic(w.x - theta_k).  The score is the expected grade.  Features are words and word beginnings,
so that inflected forms are met, as log(1 + count); those that are commoner in toxic texts are used.  The features are chosen and the model is fitted on a sample of
labelled rows of at most `fit_rows` documents (smallest hash of doc_id first); the threshold that rejects is
calibrated on a held-out fifth of them.

Where `labels` has no column `severity`, toxic documents with more indicative words than the median are graded 2.
Null and empty texts have no feature and score as clean; texts of any length are read whole.  Null labels are left out;
a document that is labelled several times has the highest of its labels; without labels all is clean.  Repeated rows are
scored alike.  `score` keeps the caller's columns, but those named like one of its own give way to it; `keep_clean` returns
all columns as they came.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import few_rows, read_table

FIT_ROWS = 20_000
FEATURES = 600
STEMS = (4, 5, 6, 7)
_WORD = re.compile(r"[^\W\d_]+")
_SUMMARY = 200_000


def features_of(word: str) -> list[str]:
    return [word, *(f"{word[:n]}~" for n in STEMS if len(word) > n)]


@dataclass
class SeverityModel:
    names: list[str] = field(default_factory=list)
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))
    thetas: np.ndarray = field(default_factory=lambda: np.array([30.0, 31.0]))
    cut: float = 0.5

    def __post_init__(self) -> None:
        self._index = {x: i for i, x in enumerate(self.names)}
        self._memo: dict[str, tuple[int, ...]] = {}

    def counts(self, text: str | None) -> Counter:
        out: Counter = Counter()
        memo, index = self._memo, self._index
        if len(memo) > _SUMMARY:
            memo.clear()
        for word in _WORD.findall((text or "").lower()):
            hit = memo.get(word)
            if hit is None:
                hit = memo[word] = tuple(index[f] for f in features_of(word) if f in index)
            if hit:
                out.update(hit)
        return out

    def above(self, text: str | None) -> np.ndarray:
        """P(grade > k) for every threshold."""
        score = sum(self.weights[i] * np.log1p(n) for i, n in self.counts(text).items())
        return 1 / (1 + np.exp(-np.clip(score - self.thetas, -40, 40)))


def fit_ordinal(x: np.ndarray, y: np.ndarray, grades: int, l2: float = 0.3, steps: int = 400) -> tuple[np.ndarray, np.ndarray]:
    """Weights and thresholds of the cumulative logit model by Adam on the full likelihood.

    Thresholds are a first value and positive gaps, so they stay ordered.
    """
    n, p = x.shape
    w, free = np.zeros(p), np.concatenate([[1.0], np.zeros(grades - 2)])
    m = [np.zeros(p), np.zeros(grades - 1)]
    v = [np.zeros(p), np.zeros(grades - 1)]
    for t in range(1, steps + 1):
        theta = np.cumsum(np.concatenate([free[:1], np.exp(free[1:])]))
        edges = np.concatenate([[-np.inf], theta, [np.inf]])
        s = (x @ w.astype(x.dtype)).astype(float)  # in the precision of x: no wider copy of it
        upper, lower = (1 / (1 + np.exp(-np.clip(edges[y + k] - s, -40, 40))) for k in (1, 0))
        d_upper, d_lower = upper * (1 - upper), lower * (1 - lower)
        like = np.maximum(upper - lower, 1e-12)
        g_w = (x.T @ ((d_upper - d_lower) / like).astype(x.dtype)).astype(float) / n + l2 * w / n
        g_theta = np.array([-(d_upper / like)[y == k].sum() + (d_lower / like)[y == k + 1].sum() for k in range(grades - 1)]) / n
        g_free = np.concatenate([[g_theta.sum()], np.exp(free[1:]) * np.cumsum(g_theta[::-1])[::-1][1:]])
        for k, g in enumerate((g_w, g_free)):
            m[k] = 0.9 * m[k] + 0.1 * g
            v[k] = 0.999 * v[k] + 0.001 * g * g
            step = 0.1 * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
            if k == 0:
                w = w - step
            else:
                free = free - step
    return w, np.cumsum(np.concatenate([free[:1], np.exp(free[1:])]))


def labelled(docs: DataFrame, labels: DataFrame, fit_rows: int) -> DataFrame:
    graded = "severity" in labels.columns
    target = F.col("severity") if graded else F.col("toxic")
    sample = (
        labels.where(F.col("doc_id").isNotNull() & target.isNotNull())
        .select(F.col("doc_id").alias("label_id"), target.cast("int").alias("target"))
        .groupBy("label_id").agg(F.max("target").alias("target"))
        .orderBy(F.xxhash64("label_id"), "label_id")
        .limit(fit_rows)
    )  # at most fit_rows rows of two numbers: safe to broadcast
    rows = docs.select(F.col("doc_id").cast("long"), "text")
    return rows.join(F.broadcast(sample), F.col("doc_id") == F.col("label_id")).select("doc_id", "text", "target")


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, features: int = FEATURES) -> SeverityModel:
    rows = labelled(few_rows(docs), labels, fit_rows)

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        toxic: Counter = Counter()

        def out() -> pa.RecordBatch:
            names = list(seen)
            batch = pa.RecordBatch.from_pydict({"name": names, "n": pa.array([seen[x] for x in names], pa.int64()), "bad": pa.array([toxic[x] for x in names], pa.int64())})
            seen.clear(), toxic.clear()
            return batch

        for batch in batches:
            for text, target in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                found = {f for word in set(_WORD.findall((text or "").lower())) for f in features_of(word)}
                seen.update(found)
                if target > 0:
                    toxic.update(found)
                if len(seen) > _SUMMARY:
                    yield out()
        yield out()

    totals = rows.agg(F.count("*").alias("n"), F.sum((F.col("target") > 0).cast("long")).alias("bad")).first()
    n, bad = totals["n"], totals["bad"] or 0
    if not bad or bad == n:
        return SeverityModel()
    counts = rows.mapInArrow(tally, "name string, n long, bad long").groupBy("name").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    expected = F.col("n") * (bad / n)
    chosen = counts.where((F.col("n") >= 3) & (F.col("bad") > expected)).orderBy(F.desc((F.col("bad") - expected) / F.sqrt(expected + 1)), "name").limit(features).collect()
    index = SeverityModel([r["name"] for r in chosen])
    indicative = {i for i, r in enumerate(chosen) if r["bad"] > 2 * r["n"] * bad / n}

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [index.counts(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_pydict(
                {"doc_id": batch.column(0), "target": batch.column(2), "at": pa.array([list(c) for c in found], pa.list_(pa.int32())), "n": pa.array([list(c.values()) for c in found], pa.list_(pa.int32()))}
            )

    got = rows.mapInArrow(vectors, "doc_id long, target int, at array<int>, n array<int>").orderBy("doc_id", "at", "n").collect()  # at most fit_rows rows of the chosen features
    x, y = np.zeros((len(got), len(chosen)), np.float32), np.array([r["target"] for r in got])
    for i, r in enumerate(got):
        x[i, r["at"]] = np.log1p(r["n"])
    if "severity" not in labels.columns:
        hits = np.array([sum(c for a, c in zip(r["at"], r["n"], strict=True) if a in indicative) for r in got])
        y = np.where(y > 0, 1 + (hits > np.median(hits[y > 0])), 0)
    held = np.array([(r["doc_id"] * 2654435761) % 5 == 0 for r in got])
    if not held.any() or held.all() or not (y[~held] > 0).any():
        held[:] = False
    w, theta = fit_ordinal(x[~held], y[~held], int(y.max()) + 1 if y.max() > 1 else 3)
    model = SeverityModel(index.names, w, theta)
    check = held if (y[held] > 0).any() else np.ones(len(y), bool)
    cut = best_cut(1 / (1 + np.exp(-np.clip(x[check] @ w.astype(x.dtype) - theta[0], -40, 40))), y[check] > 0)
    model.cut = max(cut, 1.05 * float(model.above("")[0]))  # a text without any feature is clean
    return model


def best_cut(p: np.ndarray, positive: np.ndarray) -> float:
    """The threshold of highest F1; of equally good neighbours, the middle of the gap in log odds."""
    order = np.argsort(-p, kind="stable")
    hit = np.cumsum(positive[order])
    f1 = 2 * hit / (np.arange(1, len(p) + 1) + positive.sum())
    k = int(np.argmax(f1))
    odds = np.log(np.clip(p[order], 1e-9, 1 - 1e-9) / (1 - np.clip(p[order], 1e-9, 1 - 1e-9)))
    middle = (odds[k] + odds[k + 1]) / 2 if k + 1 < len(odds) else odds[k] - 1
    return float(1 / (1 + np.exp(-middle)))


def score(docs: DataFrame, model: SeverityModel) -> DataFrame:
    """docs with expected_severity, p_toxic, grade (the most probable) and toxic (to be rejected)."""
    clash = {"expected_severity", "p_toxic", "grade", "toxic"} & set(docs.columns)
    docs = docs.drop(*clash)
    at, names = docs.columns.index("text"), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            above = np.array([model.above(t) for t in batch.column(at).to_pylist()]).reshape(batch.num_rows, len(model.thetas))
            mass = np.concatenate([np.ones((len(above), 1)), above], 1) - np.concatenate([above, np.zeros((len(above), 1))], 1)
            extra = {"expected_severity": above.sum(1), "p_toxic": above[:, 0], "grade": mass.argmax(1).astype(np.int32), "toxic": above[:, 0] >= model.cut}
            yield pa.RecordBatch.from_arrays([*batch.columns, *map(pa.array, extra.values())], [*names, *extra])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return few_rows(docs).mapInArrow(run, f"{schema}, expected_severity double, p_toxic double, grade int, toxic boolean")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    model = fit(docs, read_table(spark, sf_dir, "labels"))
    return score(docs.select("doc_id", "text"), model).drop("text")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the model does not reject, with the columns they came with."""
    model = fit(docs, read_table(spark, sf_dir, "labels"))
    return keep_clean(docs, model)


def keep_clean(docs: DataFrame, model: SeverityModel) -> DataFrame:
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([bool(model.above(t)[0] < model.cut) for t in batch.column(at).to_pylist()], pa.bool_()))

    return few_rows(docs).mapInArrow(run, docs.schema)
