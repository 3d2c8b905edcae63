"""Helpers of the training-data operators."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandloom.runtime import written

SMALL = 10_000
TOTAL_CHARS = 40_000_000


def learnable(key: Column, folds: int, held: int) -> Column:
    """True for the rows a model may learn from: crc32 of the id as text, modulo folds, is not held."""
    return F.coalesce(F.crc32(key.cast("string")) % folds != held, F.lit(False))


def held_out(key: Column, folds: int, held: int) -> Column:
    return F.coalesce(F.crc32(key.cast("string")) % folds == held, F.lit(False))


def bounded_per_class(rows: DataFrame, key: str, label: str, per_class: int) -> DataFrame:
    """At most about per_class rows of each value of a label, picked by a hash of the key; null labels have no rows.

    One pass counts the labels; a second keeps the rows whose hash lies below their label's threshold, found in the counts:
    a broadcast while there are at most SMALL of them, else a shuffled join. No group is gathered in one task, and the same
    rows come back however the input is partitioned.
    """
    span = 1 << 30
    counted = rows.where(F.col(label).isNotNull()).groupBy(F.col(label).alias("_label")).agg(F.count("*").alias("_n"))
    limits, _ = written(counted.select("_label", F.floor(F.least(F.lit(1.0), F.lit(float(per_class)) / F.col("_n")) * span).alias("_limit")), "limits")
    if limits.count() <= SMALL:
        limits = F.broadcast(limits)
    bucket = F.pmod(F.xxhash64(F.col(key), F.lit(77)), F.lit(span))
    return rows.join(limits, F.col(label) == F.col("_label")).where(bucket < F.col("_limit")).select(*[rows[c] for c in rows.columns])


def class_counts(rows: DataFrame, label: str) -> dict:
    return {r[0]: r[1] for r in rows.where(F.col(label).isNotNull()).groupBy(label).count().collect()}


def bounded_rows(rows: DataFrame, text: str, order: str, most: int) -> list:
    """Rows by their order column, streamed to the driver until their texts reach `most` characters in all."""
    out, size = [], 0
    for r in rows.orderBy(order).toLocalIterator():
        size += len(r[text])
        if out and size > most:
            break
        out.append(r)
    return out


def labelled_texts(docs: DataFrame, labels: DataFrame, label: str, folds: int, held: int, per_class: int, max_chars: int):
    """(texts, labels, class counts) to learn from, by the driver: at most about 2 * per_class whole texts of up to max_chars,
    and TOTAL_CHARS characters in all.

    Ids that carry contradictory labels teach nothing and are left out; exact copies count once.
    """
    marked = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & learnable(F.col("doc_id"), folds, held))
    picked = bounded_per_class(marked.select("doc_id", F.col(label).cast("int").alias("y")), "doc_id", "y", per_class)
    ids = picked.groupBy("doc_id").agg(F.min("y").alias("y"), F.max("y").alias("y2")).where("y = y2").select("doc_id", "y")
    counts = class_counts(marked.select(F.col(label).cast("int").alias("y")), "y")
    one_each = (
        docs.select("doc_id", "text")
        .where(F.col("text").isNotNull() & (F.length("text") <= max_chars))
        .join(F.broadcast(ids), "doc_id")  # about 2 * per_class ids
        .groupBy(F.xxhash64("text").alias("h"))
        .agg(F.min_by(F.struct("text", "y"), "doc_id").alias("r"))
        .select("r.text", "r.y", "h")
    )
    rows = bounded_rows(one_each, "text", "h", TOTAL_CHARS)
    return [r["text"] for r in rows], np.array([r["y"] for r in rows], dtype=np.int8), counts


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, l2: float = 1e-3, rounds: int = 60) -> np.ndarray:
    """Newton steps for a small dense logistic model; the last coefficient is the intercept."""
    design = np.column_stack([x, np.ones(len(x))])
    beta = np.zeros(design.shape[1])
    weight = np.ones(len(x)) if weight is None else weight
    ridge = np.full(design.shape[1], l2)
    ridge[-1] = 1e-6
    for _ in range(rounds):
        p = sigmoid(design @ beta)
        grad = design.T @ (weight * (p - y)) + ridge * beta
        hess = (design * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ design + np.diag(ridge)
        step = np.linalg.solve(hess, grad)
        beta -= np.clip(step, -8, 8)
        if np.abs(step).max() < 1e-8:
            break
    return beta
