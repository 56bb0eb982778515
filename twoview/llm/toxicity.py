"""Toxicity: embeddings of hashed subwords, averaged over a passage, feed a linear softmax; both are trained jointly.

Misspelt words share most n-grams with the words they come from, so they get a similar vector. A document
scores as its worst passage, so that length doesn't thin out a few words. Labels are known for documents only:
training first treats all passages of a toxic document as toxic, then only the one that scores highest.

Cases: null and empty texts have one empty passage and score by the bias alone. Without labelled rows of both
classes the score is the share of toxic rows, 0 if there are none. Repeated rows score alike. An empty table gives
an empty result. Other columns, labels, lang, source and doc_id are no inputs of the score.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import map_chunks
from twoview.llm.subwords import BITS, chunks_of, edges, labelled_sample, passages, places
from twoview.llm.text import Chunk

#: Words of a passage, at every size of the training set.
PASSAGE = 24
#: A passage of fewer subwords is filled up with zero vectors, so that few words alone weigh no more than among others.
FULL = 200


@dataclass
class Model:
    """Subword embeddings and the softmax on their mean; margin is what a subword adds to the odds' logarithm."""

    embedding: np.ndarray
    weights: np.ndarray
    bias: np.ndarray

    @property
    def margin(self) -> np.ndarray:
        return self.embedding @ (self.weights[:, 1] - self.weights[:, 0])


def _flat(texts: list[str], size: int, min_docs: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Subwords of passages of some texts, passage after passage, without those in fewer than min_docs texts.

    Returns the buckets left, passage bounds, text of each passage, all subwords of each passage, and the buckets known.
    Training passages don't overlap, and all of a text's take part.
    """
    buckets, lens, docs, base = [], [], [], 0
    often = np.zeros(1 << BITS, np.int32)
    for chunk in chunks_of(texts):
        p = places(chunk, once_in=size)
        doc, first, end = passages(chunk, size, size)
        a, b = edges(p, first, end)
        place = np.concatenate([x for x, _ in p.layers])
        bucket = np.concatenate([x for _, x in p.layers])
        order = np.argsort(place, kind="stable")
        place, bucket = place[order], bucket[order].astype(np.int32)
        lo = np.searchsorted(place, a)
        n = np.searchsorted(place, b) - lo
        mine = bucket[np.arange(n.sum()) + np.repeat(lo - np.cumsum(n) + n, n)]
        pairs = np.unique(mine.astype(np.int64) * chunk.n + np.repeat(doc, n))
        often += np.bincount(pairs // chunk.n, minlength=1 << BITS).astype(np.int32)
        buckets.append(mine)
        lens.append(n)
        docs.append(doc + base)
        base += chunk.n
    count = np.concatenate(lens)
    known = often >= min_docs
    kept, left = [], []
    for mine, n in zip(buckets, lens, strict=True):
        stay = known[mine]
        kept.append(mine[stay])
        left.append(_sums(stay, np.append(0, np.cumsum(n))).astype(np.int64))
    return np.concatenate(kept), np.append(0, np.cumsum(np.concatenate(left))), np.concatenate(docs), count, np.flatnonzero(known)


def _sums(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sums of values between successive bounds."""
    total = np.append(0.0, np.cumsum(values, dtype=float))
    return total[bounds[1:]] - total[bounds[:-1]]


def _blocks(bounds: np.ndarray, most: int = 1 << 20) -> list[tuple[int, int]]:
    """Runs of passages with about most subwords each, so that no array of all subwords' numbers is needed."""
    cuts = np.unique(np.append(np.searchsorted(bounds, np.arange(0, bounds[-1], most)), [0, len(bounds) - 1]))
    return list(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True))


def train(texts: list[str], y: np.ndarray, *, dim: int = 8, folds: int = 2, seed: int = 3, **options: float) -> Model:
    """Fit embeddings and softmax together to all texts, then scale them to document scores.

    The scale is cross-fitted: each fold's texts get the margins of a model of the other folds, and all these
    together set the odds, a logistic curve from the highest passage margin to the label. A class of fewer rows
    than folds is in all folds' training sets.
    """
    model = Model(np.zeros((1 << BITS, dim), np.float32), np.stack([-np.ones(dim), np.ones(dim)], 1) / (2 * np.sqrt(dim)), np.zeros(2))
    toxic = y > 0
    share = toxic.mean() if len(y) else 0.0
    if share in (0.0, 1.0):
        model.bias = np.log([max(1 - share, 1e-9), max(share, 1e-9)])
        return model
    rng = np.random.default_rng(seed)
    fold = np.full(len(y), -1)
    for k in (False, True):
        own = np.flatnonzero(toxic == k)
        if len(own) >= folds:
            fold[rng.permutation(own)] = np.arange(len(own)) % folds
    best = np.zeros(len(y))
    for f in range(folds):
        held = np.flatnonzero(fold == f)
        if len(held):
            rows, way = _fitted([texts[i] for i in np.flatnonzero(fold != f)], toxic[fold != f], model, **options)
            best[held] = _margins([texts[i] for i in held], rows @ way)
    model.embedding, way = _fitted(texts, toxic, model, **options)
    model.weights = np.stack([-way, way], 1) / 2
    if (fold < 0).any():
        rest = np.flatnonzero(fold < 0)
        best[rest] = _margins([texts[i] for i in rest], model.margin)
    slope, shift = _odds(best, toxic, 0.25)
    model.embedding *= slope
    model.bias = np.array([-shift, shift]) / 2
    return model


def _margins(texts: list[str], margin: np.ndarray) -> np.ndarray:
    return np.concatenate([best_margin(c, margin.astype(float), PASSAGE) for c in chunks_of(texts)])


def _fitted(texts: list[str], toxic: np.ndarray, start: Model, *, steps: int = 60, warm: int = 20, rate: float = 4.0, momentum: float = 0.9, min_docs: int = 3, min_share: float = 0.01, floor: float = 20.0) -> tuple[np.ndarray, np.ndarray]:
    """Embeddings, and the direction between the classes, by accelerated gradient steps.

    The gradient of a subword's embedding is the softmax's direction times the sum, over passages, of the passage's
    error by its share of the subword, so one weighted count a bucket gives all gradients. Steps are scaled by the
    subwords' mean shares. Subwords in fewer than min_docs texts keep a zero vector.
    """
    bucket, bounds, doc, count, known = _flat(texts, PASSAGE, max(min_docs, len(texts) * min_share))
    label = toxic[doc]
    slot = np.zeros(len(start.embedding), np.int32)
    slot[known] = np.arange(len(known))
    slot, inverse, blocks = slot[bucket], 1 / np.maximum(count, FULL), _blocks(bounds)

    def gathered(values: np.ndarray) -> np.ndarray:
        return np.concatenate([_sums(values[slot[bounds[a] : bounds[b]]], bounds[a : b + 1] - bounds[a]) for a, b in blocks]) if blocks else np.zeros(len(doc))

    def scattered(values: np.ndarray) -> np.ndarray:
        out = np.zeros(len(known))
        for a, b in blocks:
            out += np.bincount(slot[bounds[a] : bounds[b]], np.repeat(values[a:b], np.diff(bounds[a : b + 1])), len(known))
        return out

    use = np.ones(len(doc), bool)
    rows, way, bias = np.zeros((len(known), start.embedding.shape[1])), start.weights[:, 1] - start.weights[:, 0], -2.0
    speed = np.zeros_like(rows)
    for step in range(steps):
        ahead = rows + momentum * speed
        z = gathered(ahead @ way) * inverse
        if step == 0 or (step >= warm and step % 5 == 0):
            if step:
                best = np.lexsort((-z, doc))
                use = ~label
                use[best[np.append(True, doc[best][1:] != doc[best][:-1])]] = True
            weight = use * np.where(label, 0.5 / max((use & label).sum(), 1), 0.5 / max((use & ~label).sum(), 1))
            often = scattered(weight * inverse) + floor * 0.5 * inverse.mean() / max((use & label).sum(), 1)
        for _ in range(3):
            chance = 1 / (1 + np.exp(-np.clip(z + bias, -30, 30)))
            err = weight * (chance - label)
            bias -= err.sum() / max((weight * chance * (1 - chance)).sum(), 1e-3)
        pull = scattered(err * inverse)
        speed = momentum * speed - rate * (pull / often)[:, None] * way
        way = way - 0.01 * pull @ ahead
        rows = rows + speed
    out = np.zeros_like(start.embedding)
    out[known] = rows
    return out, way


def _odds(x: np.ndarray, y: np.ndarray, share: float) -> tuple[float, float]:
    """Slope and shift of the logistic curve from x to y, with the classes weighted to a share of y's True rows."""
    w = np.where(y, share / y.sum(), (1 - share) / (~y).sum())
    theta = np.array([1.0, -x.mean()])
    design = np.stack([x, np.ones_like(x)], 1)
    prior = np.array([1e-4, 1e-6])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(design @ theta, -30, 30)))
        grad = design.T @ (w * (p - y)) + prior * (theta - [1.0, 0.0])
        hess = (design * (w * p * (1 - p))[:, None]).T @ design + np.diag(prior)
        step = np.linalg.solve(hess, grad)
        theta = theta - np.clip(step, -2, 2)
    return float(max(theta[0], 1e-3)), float(theta[1])


def best_margin(chunk: Chunk, margin: np.ndarray, size: int) -> np.ndarray:
    """The highest mean margin of any passage of each text."""
    p = places(chunk, once_in=size)
    total, count = p.totals(margin)
    doc, first, end = passages(chunk, size, size // 2)
    a, b = edges(p, first, end)
    z = (total[b] - total[a]) / np.maximum(count[b] - count[a], FULL)
    return np.maximum.reduceat(z, np.searchsorted(doc, np.arange(chunk.n)))


def score_chunk(chunk: Chunk, margin: np.ndarray, bias: float, size: int) -> np.ndarray:
    """The highest passage probability of each text."""
    return 1 / (1 + np.exp(-np.clip(best_margin(chunk, margin, size) + bias, -40, 40)))


def toxicity(docs: DataFrame, labels: DataFrame, *, per_class: int = 1500, threshold: float = 0.3) -> DataFrame:
    """Score documents (doc_id, text) for toxicity; train on labels (doc_id, toxic), at most per_class rows a class.

    Returns doc_id, score, predicted (1 from the threshold on).
    """
    texts, y = labelled_sample(docs, labels, "toxic", per_class)
    model = train(texts, y)
    sent = docs.sparkSession.sparkContext.broadcast((model.margin.astype(np.float64), float(model.bias[1] - model.bias[0]), PASSAGE))
    scored = map_chunks(docs, "text", ["doc_id"], lambda c: {"score": score_chunk(c, *sent.value)}, "score double")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
