"""Quality: a compression classifier.

Two zstandard dictionaries are built, from good and from bad labelled texts. A whole text is compressed block by block
with each; the difference of the two compressed sizes, normalised by the text's bytes, becomes a calibrated score by a
logistic fit on labelled rows that the dictionaries have not seen (a quarter of the bounded sample).

Bounds (documented parameters): at most 2 * PER_CLASS labelled texts of up to MAX_CHARS characters, and common.TOTAL_CHARS in
all, are learned from, dictionaries hold DICT_BYTES. Scoring covers every byte of every text.

Defined results: null and empty texts have difference zero and no length, and get that point's calibrated score;
without labels of both classes the score is the share of label 1 (0.5 without labels); a class
whose texts are all empty has an empty dictionary. Scores lie in [0, 1]. Repeated rows give repeated
rows; null ids pass through; other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.llm.common import fit_logistic, held_out, labelled_texts, sigmoid
from bandloom.llm.toxicity import scored

PER_CLASS = 1500
MAX_CHARS = 50_000
DICT_BYTES = 112 * 1024
BLOCK = 2048
LEVEL = 3
FOLDS, HELD = 4, 2
THRESHOLD = 0.7


def blocks(text: str | None) -> list[bytes]:
    raw = (text or "").encode()
    return [raw[i : i + BLOCK] for i in range(0, len(raw), BLOCK)]


def dictionary(texts: list[str]) -> bytes:
    """A trained dictionary, or, where there is too little text to train on, the texts' own last bytes."""
    samples = [b for t in texts for b in blocks(t)]
    try:
        return zstandard.train_dictionary(DICT_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-DICT_BYTES:]


@dataclass
class QualityModel:
    good: bytes
    bad: bytes
    beta: np.ndarray  # a single value: the score of every text

    def __post_init__(self):
        self._coders = None

    def __getstate__(self):
        return {"good": self.good, "bad": self.bad, "beta": self.beta, "_coders": None}

    def features(self, text: str | None) -> np.ndarray:
        """The normalised size difference (bad minus good), and the same split by sign of strength."""
        if self._coders is None:
            kinds = []
            for raw in (self.good, self.bad):
                plain = {"write_content_size": False, "write_dict_id": False, "write_checksum": False}
                if raw:
                    d = zstandard.ZstdCompressionDict(raw)
                    d.precompute_compress(level=LEVEL)
                    kinds.append(zstandard.ZstdCompressor(dict_data=d, **plain))
                else:
                    kinds.append(zstandard.ZstdCompressor(level=LEVEL, **plain))
            self._coders = kinds
        good, bad = self._coders
        total = diff = 0
        for b in blocks(text):
            diff += len(bad.compress(b)) - len(good.compress(b))
            total += len(b)
        x = diff / max(total, 1)
        return np.array([x, np.clip(x, -0.05, 0.05)])

    def score(self, text: str | None) -> float:
        if len(self.beta) == 1:
            return float(self.beta[0])
        return float(sigmoid(self.features(text) @ self.beta[:-1] + self.beta[-1]))


def train(texts: list[str], y: np.ndarray, counts: dict) -> QualityModel:
    if not (y == 1).any() or not (y == 0).any():
        return QualityModel(b"", b"", np.array([float(y.mean()) if len(y) else 0.5]))
    aside = np.arange(len(y)) % 4 == 3
    if not ((y[aside] == 1).any() and (y[aside] == 0).any()):
        aside = np.ones(len(y), bool)
    build = ~aside if not aside.all() else aside
    good = dictionary([t for t, k, b in zip(texts, y, build, strict=True) if k == 1 and b])
    bad = dictionary([t for t, k, b in zip(texts, y, build, strict=True) if k == 0 and b])
    model = QualityModel(good, bad, np.zeros(3))
    x = np.array([model.features(t) for t, a in zip(texts, aside, strict=True) if a])
    z = y[aside].astype(float)
    share = {k: counts.get(k, 1) / max((z == k).sum(), 1) for k in (0, 1)}
    weight = np.where(z == 1, share[1], share[0])
    model.beta = fit_logistic(x, z, weight / weight.mean())
    return model


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, max_chars: int = MAX_CHARS) -> QualityModel:
    return train(*labelled_texts(docs, labels, "quality", FOLDS, HELD, per_class, max_chars))


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = fit(docs, labels)
    return scored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model).select(
        "doc_id", held_out(F.col("doc_id"), FOLDS, HELD).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )
