"""Language identification by error-correcting output codes.

Each learned language has a codeword of bits. One binary classifier per bit, linear in hashed character n-gram
frequencies (orders 1 to 3) of the lower-cased letters, predicts that bit; decoding weighs each bit's logistic loss by
how well its classifier did on the sample and chooses the codeword with the least loss. Up to seven languages get the
exhaustive code (2^(k-1) - 1 bits, every pair differs in about half), more get seeded random codewords of
15 * log2(k) bits, the draw whose nearest codewords are farthest apart. A prediction is flagged ambiguous when the best two losses are close.

Bounds (documented): at most about PER_LANG texts of up to MAX_CHARS characters are learned from per language, and
common.TOTAL_CHARS characters in all, in the order of a hash, so that many languages share them evenly. Any number of
languages is learned; memory grows with the code's bits, not with the languages.
Prediction covers whole texts. Defined results: null text or text without a letter is `und` with score 0.0 (and not
ambiguous); no learned language at all means `und` everywhere; one learned language is always predicted. Repeated
rows give repeated rows; null ids pass through; other columns are not read.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bandloom.llm.common import TOTAL_CHARS, bounded_per_class, bounded_rows, fit_logistic, held_out, learnable
from bandloom.llm.ngrams import code_points, pieces
from bandloom.runtime import ship, spread

BITS = 15
ORDERS = 3
PER_LANG = 400
MAX_CHARS = 20_000
FOLDS, HELD = 4, 2
MARGIN = 0.02
UND = "und"
_letters: list[np.ndarray] = []


def letter_table() -> np.ndarray:
    """True for the code points that are letters."""
    if not _letters:
        table = np.zeros(0x110000, bool)
        for c in range(0x110000):
            table[c] = unicodedata.category(chr(c))[0] == "L"
        _letters.append(table)
    return _letters[0]


def grams(text: str) -> tuple[np.ndarray, bool]:
    """Buckets of all n-grams over letters and single separators; whether there is a letter."""
    cps = code_points(text)
    letter = letter_table()[cps]
    if not letter.any():
        return np.zeros(0, np.int64), False
    cps = np.where(letter, cps, 32).astype(np.uint32)
    keep = np.ones(len(cps), bool)
    keep[1:] = letter[1:] | letter[:-1]
    cps = cps[keep]
    out, h = [], np.zeros(len(cps), np.uint32)
    for n in range(1, ORDERS + 1):
        if len(cps) < n:
            break
        h = h[: len(cps) - n + 1] * np.uint32(0x01000193) + cps[n - 1 :] + np.uint32(n)
        out.append((h * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS))
    return np.concatenate(out).astype(np.int64), True


def codewords(k: int, seed: int = 5) -> np.ndarray:
    """k distinct rows of bits; columns are distinct, not constant, and not each other's complement."""
    if k <= 1:
        return np.zeros((k, 1), np.int8)
    if k <= 7:
        cols = [[1, *((c >> i) & 1 for i in range(k - 1))] for c in range(2 ** (k - 1) - 1)]
        return np.array(cols, np.int8).T
    rng, length = np.random.default_rng(seed), int(np.ceil(15 * np.log2(k)))
    best, apart = None, 0
    for _ in range(200 if k <= 100 else 10):
        columns: dict[bytes, np.ndarray] = {}
        while len(columns) < length:
            column = rng.integers(0, 2, k, dtype=np.int8)
            if 0 < column.sum() < k:
                columns[(column ^ column[0]).tobytes()] = column  # a column and its complement have one name
        code = np.stack(list(columns.values()), 1)
        d = min(int((code[i] != code[i + 1 :]).sum(1).min()) for i in range(k - 1)) if k <= 100 else nearest(code)
        if d > apart:
            best, apart = code, d
    if best is None:
        raise RuntimeError("no draw has distinct codewords")  # k times k chances of 2^-length each
    return best


def nearest(code: np.ndarray) -> int:
    """Least Hamming distance of two rows, by blocks of inner products."""
    signs, least = 2 * code.astype(np.float32) - 1, code.shape[1]
    for at in range(0, len(signs), 512):
        d = (code.shape[1] - signs[at : at + 512] @ signs.T) / 2
        d[np.arange(len(d)), at + np.arange(len(d))] = least
        least = min(least, int(d.min()))
    return least


@dataclass
class LangModel:
    langs: list[str]
    code: np.ndarray
    table: np.ndarray  # buckets x bits
    scale: np.ndarray
    shift: np.ndarray
    trust: np.ndarray

    def margins(self, text: str | None) -> np.ndarray | None:
        """Each bit's logit, or None without a letter."""
        total, n = np.zeros(self.table.shape[1]), 0
        for piece in pieces((text or "").lower()):
            g, _ = grams(piece)
            if len(g):
                total += self.table[g].sum(0, dtype=np.float64)
                n += len(g)
        return self.scale * total / n + self.shift if n else None

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        m = self.margins(text)
        if m is None or not self.langs:
            return UND, 0.0, False
        sign = 2.0 * self.code - 1
        loss = (self.trust * np.logaddexp(0, -sign * m)).sum(1)
        order = np.argsort(loss, kind="stable")
        p = np.exp(-(loss - loss[order[0]]))
        gap = 1.0 if len(order) == 1 else (loss[order[1]] - loss[order[0]]) / self.trust.sum()
        return self.langs[order[0]], float(p[order[0]] / p.sum()), bool(gap < MARGIN)


def train(texts: list[str], langs: list[str]) -> LangModel:
    known = sorted(set(langs))
    code = codewords(len(known))
    if len(known) <= 1:
        one = np.zeros((1 << BITS, 1), np.float32)
        return LangModel(known, code, one, np.ones(1), np.zeros(1), np.ones(1))
    number = {x: i for i, x in enumerate(known)}
    at = np.array([number[x] for x in langs])
    # Mean n-gram shares of the languages on each side of every bit, one language at a time; texts are cut up twice, not kept.
    sums = np.zeros((2, code.shape[1], 1 << BITS))
    for k, word in enumerate(code):
        own = np.zeros(1 << BITS)
        for i in np.flatnonzero(at == k):
            b = grams(texts[i].lower())[0]
            own += np.bincount(b, minlength=1 << BITS) / max(len(b), 1)
        own /= max(own.sum(), 1e-12)
        for side in (0, 1):
            sums[side, word == side] += own
    floor = 1e-6
    ones = code.sum(0, dtype=np.int64)[:, None]
    table = np.ascontiguousarray((np.log(sums[1] / ones + floor) - np.log(sums[0] / (len(known) - ones) + floor)).T.astype(np.float32))
    del sums
    bags = (grams(t.lower())[0] for t in texts)
    means = [table[b].mean(0) if len(b) else None for b in bags]
    full = np.array([m is not None for m in means])
    if not full.any():  # not a letter in any text: nothing tells the languages apart
        return LangModel(known, code, table, np.ones(code.shape[1]), np.zeros(code.shape[1]), np.ones(code.shape[1]))
    x = np.array([m for m in means if m is not None])
    scale, shift, trust = [], [], []
    for j, bit in enumerate(code.T):
        y = bit[at[full]].astype(float)
        beta = fit_logistic(x[:, [j]], y, l2=1e-2)
        scale.append(beta[0])
        shift.append(beta[1])
        trust.append(max(((x[:, j] * beta[0] + beta[1] > 0) == (y > 0.5)).mean() - 0.5, 0.01))
    trust = np.array(trust)
    return LangModel(known, code, table, np.array(scale), np.array(shift), trust / trust.mean())


def fit(docs: DataFrame, per_lang: int = PER_LANG, max_chars: int = MAX_CHARS) -> LangModel:
    usable = docs.where(F.col("text").isNotNull() & F.col("lang").isNotNull() & learnable(F.col("doc_id"), FOLDS, HELD))
    usable = usable.where(F.length("text") <= max_chars).select("doc_id", "text", "lang")
    some = bounded_per_class(usable, "doc_id", "lang", per_lang).groupBy(F.xxhash64("text", "lang").alias("h")).agg(F.first("text").alias("text"), F.first("lang").alias("lang"))
    rows = bounded_rows(some, "text", "h", TOTAL_CHARS)
    return train([r["text"] for r in rows], [r["lang"] for r in rows])


def identified(docs: DataFrame, model: LangModel, prefix: str = "") -> DataFrame:
    """All columns of docs (but those with the new names), with lang_pred, score and ambiguous under the prefix."""
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)  # 2^BITS weights per code bit
    names = [prefix + n for n in ("lang_pred", "score", "ambiguous")]

    def run(it):
        m = shared.value
        for batch in it:
            at = batch.schema.get_field_index("text")
            got = [m.predict(t.as_py()) for t in batch.column(at)]
            cols = [pa.array([g[i] for g in got], kind) for i, kind in enumerate((pa.string(), pa.float64(), pa.bool_()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *cols], [*batch.schema.names, *names])

    plain = spread(docs.drop(*names))
    added = [T.StructField(n, t()) for n, t in zip(names, (T.StringType, T.DoubleType, T.BooleanType), strict=True)]
    return plain.mapInArrow(run, T.StructType([*plain.schema.fields, *added]))


def language_id(docs: DataFrame) -> DataFrame:
    got = identified(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), fit(docs))
    return got.select("doc_id", held_out(F.col("doc_id"), FOLDS, HELD).alias("held_out"), "lang_pred", "score", "ambiguous")
