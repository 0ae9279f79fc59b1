"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features are presences of hashed words, bigrams and skip-bigrams (one or two words left out). Per-coordinate rates and an L1 penalty leave
a few thousand weights, which are shipped with the scoring task. Labels are learnt from a bounded sample of rows outside the held-out third; every whole
text is scored, however long. Null and empty texts get the score of the bias alone; repeated rows and equal texts are scored alike; without labelled rows all scores are 0.5;
an empty table gives an empty result; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import hashes, labelled_sample, words

BITS, SAMPLE_ROWS, LONGEST = 20, 8000, 20_000
BIAS = 0
_MIX = np.uint64(0x9E3779B97F4A7C15)


def held_out(doc_id):
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 3 == 1


def feature_ids(text: str | None) -> np.ndarray:
    """Hashed features with repeats; id 0 is the bias and left out."""
    h = hashes(words(text))
    grams = [h] + [h[: -k or None] * np.uint64(2 * k + 1) + (h[k:] << np.uint64(7)) * np.uint64(31) + np.uint64(k) for k in (1, 2, 3) if len(h) > k]
    mixed = (np.concatenate(grams) * _MIX) >> np.uint64(64 - BITS)
    return np.maximum(mixed, np.uint64(1)).astype(np.int64)


class Ftrl:
    def __init__(self, alpha: float = 2.0, beta: float = 1.0, l1: float = 6.0, l2: float = 0.5):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros(1 << BITS), np.zeros(1 << BITS)

    def weights(self, at) -> np.ndarray:
        z, l1 = self.z[at], np.where(np.asarray(at) == BIAS, 0.0, self.l1)
        return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((self.beta + np.sqrt(self.n[at])) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, label: int) -> None:
        w = self.weights(at)
        g = 1 / (1 + math.exp(-max(-35.0, min(35.0, w.sum())))) - label
        root = np.sqrt(self.n[at])
        self.z[at] += g - (np.sqrt(self.n[at] + g * g) - root) / self.alpha * w
        self.n[at] += g * g

    def sparse(self) -> tuple[np.ndarray, np.ndarray]:
        w = self.weights(np.arange(1 << BITS))
        at = np.flatnonzero(w)
        return at, w[at]


def train(rows: list[tuple[str, int]], epochs: int = 4) -> tuple[np.ndarray, np.ndarray]:
    model, ready = Ftrl(), [(np.unique(np.append(feature_ids(text), BIAS)), int(label)) for text, label in rows]
    for _ in range(epochs):
        for at, label in ready:
            model.learn(at, label)
    return model.sparse()


def scorer(model: tuple[np.ndarray, np.ndarray]):
    """text -> score."""
    table = np.zeros(1 << BITS)
    table[model[0]] = model[1]
    hit = table != 0

    def score(text: str | None) -> float:
        ids = feature_ids(text)
        total = table[BIAS] + table[np.unique(ids[hit[ids]])].sum()
        return 1 / (1 + math.exp(-max(-35.0, min(35.0, total))))

    return score


def fit(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, longest: int = LONGEST) -> tuple[np.ndarray, np.ndarray]:
    sample = labelled_sample(docs, labels, ["toxic"], rows, longest, ~held_out(F.col("doc_id")))
    return train([(r["text"], r["toxic"]) for r in sample])


def scored(docs: DataFrame, model: tuple[np.ndarray, np.ndarray], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score): one row per row of docs."""

    def run(batches):
        score = scorer(model)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([score(t) for t in batch.column(1).to_pylist()], pa.float64())], ["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, score double")
