"""Quality by ordinal cumulative-link regression on graded ratings.

One vector of weights over hashed text is shared by all grades; ordered thresholds cut its value into grades, so P(grade > k) = s(w.x - t_k). Features are square roots
of shares: hashed words, hashed token shapes, and words that repeat the word before. Trained on a bounded sample, every whole text is scored: expected
grade and the tail probability of reaching a grade, by which documents are selected.

Null and empty texts have no features and get the grade of the thresholds alone; repeated rows and equal texts score alike; without ratings everything is kept; an empty
table gives an empty result; texts of any length are scored whole; `selected` passes all columns as they came, `graded` replaces given columns of its results' names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import hashes, labelled_sample, shapes, words

BITS, SAMPLE_ROWS, LONGEST = 16, 4000, 20_000
WORD_SCALE, SHAPE_SCALE, REPEAT_SCALE = 0.5, 1.0, 2.0


def vector(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(ids, values)."""
    parts_at, parts_x = [np.zeros(0, np.int64)], [np.zeros(0)]
    h = hashes(words(text))
    for kind, (tokens, scale) in enumerate(((h, WORD_SCALE), (hashes(shapes(text)), SHAPE_SCALE))):
        if len(tokens):
            at, count = np.unique((tokens * np.uint64(2) + np.uint64(kind)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - BITS), return_counts=True)
            parts_at.append(at.astype(np.int64))
            parts_x.append(scale * np.sqrt(count / len(tokens)))
    repeats = np.count_nonzero(h[1:] == h[:-1]) / max(1, len(h))
    parts_at.append(np.array([1 << BITS]))
    parts_x.append(np.array([REPEAT_SCALE * np.sqrt(repeats)]))
    return np.concatenate(parts_at), np.concatenate(parts_x)


class Ordinal:
    """w, and thresholds t_0 < t_1 < ... kept in order as a first threshold and positive gaps."""

    def __init__(self, grades: int):
        self.w, self.first, self.gaps = np.zeros((1 << BITS) + 1), 0.0, np.ones(max(0, grades - 2))

    @property
    def thresholds(self) -> np.ndarray:
        return self.first + np.concatenate([[0.0], np.cumsum(self.gaps)])

    def tails(self, value: float) -> np.ndarray:
        """P(grade > k) for each k."""
        return 1 / (1 + np.exp(-np.clip(value - self.thresholds, -35, 35)))


def train(rows: list[tuple[str, int]], grades: int, epochs: int = 12, rate: float = 0.5, l2: float = 1e-5) -> Ordinal:
    """Adagrad on the log-likelihood; each grade's probability is the difference of neighbouring tails."""
    model, ready = Ordinal(grades), [(*vector(text), int(grade)) for text, grade in rows]
    seen_w, seen_t = np.full(len(model.w), 1e-6), np.full(grades - 1, 1e-6)
    for epoch in range(epochs):
        for at, x, grade in ready:
            tail = model.tails(model.w[at] @ x)
            bounds = np.concatenate([[1.0], tail, [0.0]])
            chance = max(1e-9, bounds[grade] - bounds[grade + 1])
            slope = np.concatenate([[0.0], tail * (1 - tail), [0.0]])
            g = -(slope[grade] - slope[grade + 1]) / chance  # by the value
            step = g * x + l2 * model.w[at]
            seen_w[at] += step * step
            model.w[at] -= rate * step / np.sqrt(seen_w[at])
            by_threshold = np.zeros(grades - 1)
            if grade:
                by_threshold[grade - 1] += slope[grade] / chance
            if grade < grades - 1:
                by_threshold[grade] -= slope[grade + 1] / chance
            by_gap = np.cumsum(by_threshold[::-1])[::-1]
            seen_t += by_gap * by_gap
            move = rate * by_gap / np.sqrt(seen_t)
            model.first -= move[0]
            model.gaps = np.maximum(1e-3, model.gaps - move[1:])
    return model


def fit(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, longest: int = LONGEST) -> Ordinal:
    """Grades 0, 1, 2: low quality; good but marked toxic; good."""
    sample = labelled_sample(docs, labels, ["quality", "toxic"], rows, longest)
    return train([(r["text"], r["quality"] * (2 - r["toxic"])) for r in sample], 3)


def graded(docs: DataFrame, model: Ordinal, reach: int = 1) -> DataFrame:
    """docs with expected_grade and tail (the probability of grade >= reach) beside each row; given columns of these names give way."""
    docs = docs.drop("expected_grade", "tail")
    at = docs.columns.index("text")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields) + ", expected_grade double, tail double"
    keep = np.flatnonzero(model.w)
    packed = (keep, model.w[keep].astype(np.float32), model.first, model.gaps)

    def run(batches):
        local = Ordinal(len(packed[3]) + 2)
        local.w[packed[0]], local.first, local.gaps = packed[1], packed[2], packed[3]
        for batch in batches:
            tails = [local.tails(local.w[i] @ x) for i, x in map(vector, batch.column(at).to_pylist())]
            grades, tail = pa.array([float(t.sum()) for t in tails], pa.float64()), pa.array([float(t[reach - 1]) for t in tails], pa.float64())
            yield batch.append_column("expected_grade", grades).append_column("tail", tail)

    return docs.mapInArrow(run, fields)


def selected(docs: DataFrame, labels: DataFrame, least: float = 0.5, reach: int = 1) -> DataFrame:
    """docs whose tail probability is at least `least`, with the columns of docs."""
    held = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("given"), "text")
    return graded(held, fit(docs, labels), reach).filter(F.col("tail") >= least).select(*(F.col(f"given.`{c}`").alias(c) for c in docs.columns))
