"""Toxicity: a linear classifier on character n-grams whose features are scaled by naive Bayes log-count ratios.

Features are presences of n-grams of 4 to 6 characters in the lower-cased text, with runs of white space as one space.
Training takes at most 2 * PER_CLASS labelled texts of up to MAX_CHARS characters, and common.TOTAL_CHARS in all (documented
bounds; scoring has none). From their document counts each feature gets the log ratio of its smoothed class frequencies; the features with
the largest likelihood-ratio statistic are kept by exact 64-bit hash, scaled by their ratio, and weighed by L2-
regularised logistic regression.

Defined results: null and empty texts get the model's base score (no feature present); without labels of both
classes every score is 0.0. Repeated rows give repeated rows; null ids pass through; other columns are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bandloom.llm.common import held_out, labelled_texts, sigmoid
from bandloom.llm.ngrams import hashed, pieces
from bandloom.runtime import ship, spread

ORDERS = (4, 5, 6)
PER_CLASS = 2000
MAX_CHARS = 50_000
FEATURES = 6_000
FOLDS, HELD = 3, 1
THRESHOLD = 0.7
BITS = 20
SPACE = re.compile(r"\s+")


def normal(text: str | None) -> str:
    return " " + SPACE.sub(" ", (text or "").lower()).strip() + " " if text else ""


@dataclass
class ToxicModel:
    features: np.ndarray  # sorted 64-bit hashes
    weights: np.ndarray
    bias: float | None  # None: nothing was learned

    def __post_init__(self):
        self.near = np.zeros(1 << BITS, bool)
        self.near[(self.features >> np.uint64(64 - BITS)).astype(np.int64)] = True

    def present(self, text: str | None) -> np.ndarray:
        """Positions in features of those that the text holds."""
        found = []
        for piece in pieces(normal(text)):
            h = hashed(piece, ORDERS)
            found.append(h[self.near[(h >> np.uint64(64 - BITS)).view(np.int64)]])
        h = np.unique(np.concatenate(found)) if found else np.zeros(0, np.uint64)
        if not len(h) or not len(self.features):
            return np.zeros(0, np.int64)
        at = np.minimum(np.searchsorted(self.features, h), len(self.features) - 1)
        return at[self.features[at] == h]

    def score(self, text: str | None) -> float:
        if self.bias is None:
            return 0.0
        return float(sigmoid(self.weights[self.present(text)].sum() + self.bias))


def likelihood(a: np.ndarray, b: np.ndarray, na: int, nb: int) -> np.ndarray:
    """Twice the log-likelihood gain of separate rates a/na and b/nb over a common one."""

    def part(k, n, p):
        p = np.clip(p, 1e-12, 1 - 1e-12)
        return k * np.log(p) + (n - k) * np.log1p(-p)

    both = (a + b) / (na + nb)
    return 2 * (part(a, na, a / na) + part(b, nb, b / nb) - part(a, na, both) - part(b, nb, both))


def train(texts: list[str], y: np.ndarray, counts: dict) -> ToxicModel:
    """counts: rows of each class among all that may be learned from; sets the intercept's prior."""
    if not (y == 1).any() or not (y == 0).any():
        return ToxicModel(np.zeros(0, np.uint64), np.zeros(0), None)
    n1, n0 = int((y == 1).sum()), int((y == 0).sum())
    # First pass: document counts by 22-bit bucket, to tell which n-grams are worth keeping by their whole hash.
    df = np.zeros((2, 1 << 22), np.int32)
    for t, label in zip(texts, y, strict=True):
        df[label, np.unique(hashed(normal(t), ORDERS) >> np.uint64(42)).astype(np.int64)] += 1
    least = max(3, round(0.004 * n1))
    often = np.flatnonzero((df[1] >= least) & (df[1] * n0 > df[0].astype(np.int64) * n1) | (df[0] >= max(8, 0.01 * n0)))
    gain = likelihood(df[1, often].astype(float), df[0, often].astype(float), n1, n0)
    good = np.argsort(-gain, kind="stable")[: 2 * FEATURES]
    keep = np.zeros(1 << 22, bool)
    keep[often[good[gain[good] > 16.0]]] = True
    del df
    rows = [h[keep[(h >> np.uint64(42)).astype(np.int64)]] for h in (np.unique(hashed(normal(t), ORDERS)) for t in texts)]
    every, at = np.unique(np.concatenate(rows), return_inverse=True)
    doc = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    label = y[doc]
    a = np.bincount(at[label == 1], minlength=len(every)).astype(float)
    b = np.bincount(at[label == 0], minlength=len(every)).astype(float)
    gain = likelihood(a, b, n1, n0)
    top = np.sort(np.argsort(-gain, kind="stable")[:FEATURES])
    top = top[gain[top] > 16.0]
    ratio = np.log((a[top] + 1) / (n1 + 2)) - np.log((b[top] + 1) / (n0 + 2))
    place = np.full(len(every), -1)
    place[top] = np.arange(len(top))
    use = place[at] >= 0
    doc, col = doc[use], place[at][use]
    # NB-scaled logistic regression, full-batch with an adaptive step; each row weighs as its class does in all labels.
    weight = np.where(y == 1, counts.get(1, n1) / n1, counts.get(0, n0) / n0)
    weight = weight / weight.sum()
    w, bias = np.zeros(len(top)), float(np.log(max(counts.get(1, n1), 1) / max(counts.get(0, n0), 1)))
    size, size_b = np.full(len(top), 1e-8), 1e-8
    for _ in range(150):
        z = np.bincount(doc, w[col] * ratio[col], minlength=len(y)) + bias
        d = weight * (sigmoid(z) - y)
        g = np.bincount(col, d[doc] * ratio[col], minlength=len(top)) + 2e-5 * w
        size += g * g
        size_b += d.sum() ** 2
        w -= 0.1 * g / np.sqrt(size)
        bias -= 0.1 * d.sum() / np.sqrt(size_b)
    return ToxicModel(every[top], w * ratio, bias)


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, max_chars: int = MAX_CHARS) -> ToxicModel:
    return train(*labelled_texts(docs, labels, "toxic", FOLDS, HELD, per_class, max_chars))


def scored(docs: DataFrame, model, out: str = "score") -> DataFrame:
    """All columns of docs (but one named `out`) and the model's score of the whole text. model: anything with score(text)."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)  # at most FEATURES weights

    def run(it):
        m = shared.value
        for batch in it:
            at = batch.schema.get_field_index("text")
            score = pa.array([m.score(t.as_py()) for t in batch.column(at)], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, score], [*batch.schema.names, out])

    plain = spread(docs.drop(out))
    return plain.mapInArrow(run, T.StructType([*plain.schema.fields, T.StructField(out, T.DoubleType())]))


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = fit(docs, labels)
    return scored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model).select(
        "doc_id", held_out(F.col("doc_id"), FOLDS, HELD).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )
