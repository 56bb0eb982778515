"""Quality grades by ordinal regression: one weight vector on hashed text, and ordered thresholds between grades.

The chance of a grade of k or less is the logistic function of threshold k minus the text's value, which is
the mean weight of its hashed words and n-grams. All grades share the weights; the thresholds stay in order
because training moves the first and the logarithms of the gaps.

Cases: null and empty texts have value 0. Without rated rows all grades but the lowest are impossible; with one
grade only, that grade is sure. Repeated rows are graded alike. An empty table gives an empty result. Other
columns are left out of account.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import map_chunks
from twoview.llm.subwords import BITS, chunks_of, labelled_sample, places
from twoview.llm.text import Chunk

SIZES = (3, 4)


@dataclass
class Grader:
    """weights by bucket; thresholds below each grade but the lowest; the grades, ascending."""

    weights: np.ndarray
    thresholds: np.ndarray
    grades: np.ndarray

    def tails(self, value: np.ndarray) -> np.ndarray:
        """Chance of each grade or more but the lowest, one row a text."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None] - value[:, None], -40, 40)))

    def value(self, chunk: Chunk) -> np.ndarray:
        p = places(chunk, SIZES, lower=False)
        total, count = p.totals(self.weights)
        edge = chunk.off + np.arange(chunk.n + 1)
        return (total[edge[1:]] - total[edge[:-1]]) / np.maximum(count[edge[1:]] - count[edge[:-1]], 1)


def train(texts: list[str], y: np.ndarray, *, epochs: int = 12, rate: float = 20.0, batch: int = 64, seed: int = 5) -> Grader:
    """Fit weights and thresholds to the grades y by row-wise scaled gradient steps."""
    grades = np.unique(y) if len(y) else np.array([0])
    model = Grader(np.zeros(1 << BITS), np.zeros(len(grades) - 1), grades)
    if len(grades) < 2:
        return model
    rank = np.searchsorted(grades, y)
    rows = []
    for chunk in chunks_of(texts):
        p = places(chunk, SIZES, lower=False)
        edge = chunk.off + np.arange(chunk.n + 1)
        place = np.concatenate([a for a, _ in p.layers])
        bucket = np.concatenate([b for _, b in p.layers])
        order = np.argsort(place, kind="stable")
        place, bucket = place[order], bucket[order]
        cut = np.searchsorted(place, edge)
        for i in range(chunk.n):
            ids, n = np.unique(bucket[cut[i] : cut[i + 1]], return_counts=True)
            rows.append((ids.astype(np.int32), n / max(n.sum(), 1)))
    share = np.clip(np.cumsum(np.bincount(rank, minlength=len(grades)))[:-1] / len(y), 1e-3, 1 - 1e-3)
    logit = np.log(share / (1 - share))
    lowest, gaps = logit[0], np.log(np.maximum(np.diff(logit), 1e-2))
    rng = np.random.default_rng(seed)
    scale, t_scale = np.full(1 << BITS, 1e-10), np.full(len(logit), 1e-2)
    for _ in range(epochs):
        for part in np.array_split(rng.permutation(len(rows)), max(1, len(rows) // batch)):
            theta = lowest + np.append(0, np.cumsum(np.exp(gaps)))
            ids = np.concatenate([rows[i][0] for i in part])
            tf = np.concatenate([rows[i][1] for i in part])
            who = np.repeat(np.arange(len(part)), [len(rows[i][0]) for i in part])
            s = np.bincount(who, model.weights[ids] * tf, len(part))
            cdf = 1 / (1 + np.exp(np.clip(s[:, None] - theta[None], -30, 30)))
            full = np.concatenate([np.zeros((len(part), 1)), cdf, np.ones((len(part), 1))], 1)
            r = rank[part]
            rows_at = np.arange(len(part))
            low, high = full[rows_at, r], full[rows_at, r + 1]
            chance = np.maximum(high - low, 1e-9)
            d_high, d_low = high * (1 - high) / chance, low * (1 - low) / chance
            pull = d_high - d_low
            touched, slot = np.unique(ids, return_inverse=True)
            g = np.bincount(slot, pull[who] * tf, len(touched))
            scale[touched] += g**2
            model.weights[touched] -= rate * g / np.sqrt(scale[touched])
            g_theta = np.zeros(len(theta))
            np.add.at(g_theta, r[r < len(theta)], -d_high[r < len(theta)])
            np.add.at(g_theta, r[r > 0] - 1, d_low[r > 0])
            back = np.cumsum(g_theta[::-1])[::-1]
            g_all = np.append(back[0], back[1:] * np.exp(gaps)) / len(part)
            t_scale += g_all**2
            move = 0.2 * g_all / np.sqrt(t_scale)
            lowest -= move[0]
            gaps = np.clip(gaps - move[1:], -5, 5)
    model.thresholds = lowest + np.append(0, np.cumsum(np.exp(gaps)))
    return model


def quality_grades(docs: DataFrame, ratings: DataFrame, *, per_grade: int = 1500, select_grade: int = 1, min_tail: float = 0.5) -> DataFrame:
    """Grade documents (doc_id, text); train on ratings (doc_id, grade), at most per_grade rows a grade.

    Returns doc_id, value, expected_grade, tail (chance of select_grade or more), selected (tail of min_tail or more).
    """
    texts, y = labelled_sample(docs, ratings, "grade", per_grade)
    model = train(texts, y)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def grade(chunk: Chunk) -> dict[str, np.ndarray]:
        m = sent.value
        value = m.value(chunk)
        tails = m.tails(value)
        expected = m.grades[0] + tails @ np.diff(m.grades)
        over = np.flatnonzero(m.grades >= select_grade)
        tail = np.zeros(chunk.n) if not len(over) else np.ones(chunk.n) if over[0] == 0 else tails[:, over[0] - 1]
        return {"value": value, "expected_grade": expected, "tail": tail}

    out = map_chunks(docs, "text", ["doc_id"], grade, "value double, expected_grade double, tail double")
    return out.withColumn("selected", F.col("tail") >= min_tail)
