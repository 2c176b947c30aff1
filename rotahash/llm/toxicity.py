"""Toxicity by a chain of linear classifiers.

The categories are predicted one after another. The model of a category sees the words of a text and
the probabilities that the models before it gave; while training these are out-of-fold predictions, so
that a later model does not rely on answers its predecessors have memorised.

Only the fit works on a bounded sample: the ``sample_rows`` labelled documents whose hashed id is least
(a documented parameter, the same documents in every run). Prediction reads every whole text.

Defined results: null or empty text has no words, so its probability is the models' intercept; labels
that are null are left out for their category; with no usable label of a category (or only one class)
its probability is the share of positives among the labels (0 without labels). A document labelled
more than once is trained on once per label row. Columns of ``docs`` beyond doc_id and text are
ignored by ``predict`` and kept by ``reject``.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, distinct_sorted, lean, slices, word_hashes

BITS = 20
SAMPLE_ROWS = 8192
THRESHOLD = 0.25


@dataclass
class Linear:
    """Weights of hashed words (sorted by word) and of the earlier categories' probabilities."""

    words: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))
    chain: np.ndarray = field(default_factory=lambda: np.zeros(0))
    bias: float = 0.0
    constant: float | None = None

    def score(self, dense: np.ndarray, values: np.ndarray, at: np.ndarray, earlier: np.ndarray) -> np.ndarray:
        n = len(at) - 1
        if self.constant is not None:
            return np.full(n, self.constant)
        sums = np.concatenate([[0.0], np.cumsum(dense[values])])
        z = sums[at[1:]] - sums[at[:-1]] + self.bias + (earlier @ self.chain if len(self.chain) else 0)
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << BITS)
        out[self.words] = self.weights
        return out


def features(column) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed words of each text, folded to 2^BITS."""
    values, ends = [np.zeros(0, np.int64)], [np.zeros(1, np.int64)]
    for _, _, data, at in slices(column, lower=True):
        words, rows = word_hashes(data, at)
        v, a = distinct_sorted((words >> U(64 - BITS)).astype(np.int64), rows)
        ends.append(a[1:] + sum(map(len, values)))
        values.append(v)
    return np.concatenate(values), np.concatenate(ends)


def _fit(values: np.ndarray, at: np.ndarray, y: np.ndarray, earlier: np.ndarray, keep: int, steps: int, decay: float) -> Linear:
    """Ridge-penalised logistic regression on the words that tell the classes apart best, by accelerated full-batch gradient descent."""
    n, pos = len(y), y.sum()
    if pos == 0 or pos == n:
        return Linear(constant=float(pos / n) if n else 0.0)
    row = np.repeat(np.arange(n), np.diff(at))
    seen = np.bincount(values, minlength=1 << BITS)
    hits = np.bincount(values, weights=y[row], minlength=1 << BITS)
    expect = seen * pos / n
    chi = np.where(seen >= 4, (hits - expect) ** 2 / np.maximum(expect * (1 - pos / n), 1e-9), 0)
    words = np.sort(np.argsort(-chi, kind="stable")[:keep])
    words = words[chi[words] > 4]
    place = np.full(1 << BITS, -1)
    place[words] = np.arange(len(words))
    col = place[values]
    row, col = row[col >= 0], col[col >= 0]
    m, c = len(words), earlier.shape[1]
    w = np.zeros(m + c + 1)
    v, rate = w.copy(), 4.0 / (1 + (len(row) / max(n, 1)))
    for t in range(steps):
        z = np.bincount(row, weights=v[col], minlength=n) + earlier @ v[m : m + c] + v[-1]
        g = (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y) / n
        grad = np.concatenate([np.bincount(col, weights=g[row], minlength=m), earlier.T @ g, [g.sum()]])
        grad[:-1] += decay * v[:-1]
        step = v - rate * grad
        v, w = step + t / (t + 3) * (step - w), step
    return Linear(words, w[:m], w[m : m + c], float(w[-1]))


def fit(docs: DataFrame, labels: DataFrame, categories: tuple[str, ...], sample_rows: int = SAMPLE_ROWS, folds: int = 4, keep: int = 256, steps: int = 600, decay: float = 1e-5) -> list[Linear]:
    """Models of the categories in the chain's order, from a bounded sample of labelled documents."""
    chosen = labels.select("doc_id", *categories).where(F.col("doc_id").isNotNull()).orderBy(F.xxhash64("doc_id"), "doc_id", *categories).limit(sample_rows)
    rows = F.broadcast(chosen.select(F.col("doc_id").alias("_id"), *(F.col(c).cast("double").alias(f"_{i}") for i, c in enumerate(categories))))
    joined = docs.select("doc_id", "text").join(rows, F.col("doc_id") == F.col("_id")).select("doc_id", "text", *(f"_{i}" for i in range(len(categories))))

    def extract(batches):
        for b in batches:
            values, at = features(b.column("text"))
            cells = [values[at[i] : at[i + 1]].astype(np.int32).tobytes() for i in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(cells, pa.binary()), *(b.column(f"_{i}") for i in range(len(categories)))], ["doc_id", "words", *(f"_{i}" for i in range(len(categories)))])

    kinds = "doc_id long, words binary, " + ", ".join(f"_{i} double" for i in range(len(categories)))
    got = sorted(joined.mapInArrow(lean(extract), kinds).collect(), key=lambda r: (r.doc_id, r.words))
    cells = [np.frombuffer(r.words, np.int32).astype(np.int64) for r in got]
    ids = np.array([r.doc_id for r in got], np.int64)
    fold = (ids.astype(U) * U(0x9E3779B97F4A7C15) >> U(40)).astype(np.int64) % folds
    chain = np.zeros((len(got), 0))
    models = []
    for i, _ in enumerate(categories):
        y = np.array([np.nan if r[f"_{i}"] is None else r[f"_{i}"] for r in got], float)
        known = ~np.isnan(y)

        def part(mask, y=y, chain=chain):
            take = np.flatnonzero(mask)
            own = [cells[j] for j in take]
            at = np.concatenate([[0], np.cumsum([len(x) for x in own])]).astype(np.int64)
            return (np.concatenate(own) if own else np.zeros(0, np.int64)), at, (y[take] > 0.5).astype(float), chain[take]

        models.append(_fit(*part(known), keep, steps, decay))
        if i + 1 < len(categories):
            out = np.zeros(len(got))
            for f in range(folds):
                held = fold == f
                model = _fit(*part(known & ~held), keep, steps, decay)
                values, at, _, earlier = part(held)
                out[held] = model.score(model.dense(), values, at, earlier)
            chain = np.column_stack([chain, out])
    return models


def predict(docs: DataFrame, models: list[Linear], categories: tuple[str, ...]) -> DataFrame:
    """doc_id and ``p_<category>`` of every document; the models' size is bounded by ``keep``."""
    shared = docs.sparkSession.sparkContext.broadcast(models)

    def score(batches):
        dense = [m.dense() for m in shared.value]
        for b in batches:
            values, at = features(b.column("text"))
            chain = np.zeros((b.num_rows, 0))
            for m, d in zip(shared.value, dense, strict=True):
                chain = np.column_stack([chain, m.score(d, values, at, chain)])
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(chain[:, i]) for i in range(len(dense)))], ["doc_id", *(f"p_{c}" for c in categories)])

    return docs.select("doc_id", "text").mapInArrow(lean(score), "doc_id long, " + ", ".join(f"p_{c} double" for c in categories))


def classify(docs: DataFrame, labels: DataFrame, categories: tuple[str, ...] = ("quality", "toxic"), threshold: float = THRESHOLD, **options) -> DataFrame:
    """One row per document: the chain's probabilities and whether the last category's reaches the threshold."""
    scored = predict(docs, fit(docs, labels, categories, **options), categories)
    return scored.withColumn("rejected", F.col(f"p_{categories[-1]}") >= threshold)


def reject(docs: DataFrame, labels: DataFrame, categories: tuple[str, ...] = ("quality", "toxic"), threshold: float = THRESHOLD, **options) -> DataFrame:
    """The rows of docs that are not toxic, all columns as they were; decided text by text, with no join."""
    models = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, categories, **options))

    def keep(batches):
        dense = [m.dense() for m in models.value]
        for b in batches:
            values, at = features(b.column("text"))
            chain = np.zeros((b.num_rows, 0))
            for m, d in zip(models.value, dense, strict=True):
                chain = np.column_stack([chain, m.score(d, values, at, chain)])
            yield b.filter(pa.array(chain[:, -1] < threshold))

    return docs.mapInArrow(lean(keep), docs.schema)
