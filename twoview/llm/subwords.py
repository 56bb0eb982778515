"""Hashed subwords (whole words and character n-grams) as places in a chunk, for linear models on texts.

Each subword sits at one place of a padded copy of the chunk, in which a blank stands before and after each text
and so marks the edges of words. Sums over any run of words are then differences of one running sum.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import has_columns
from twoview.llm.text import Chunk, column_chunks, mix, powers

BITS = 18


@dataclass
class Places:
    """Subwords of a chunk: place and bucket of each, and the places where each word starts and ends."""

    size: int
    layers: list[tuple[np.ndarray, np.ndarray]]
    starts: np.ndarray
    ends: np.ndarray

    def totals(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Running sums, by place, of the buckets' values and of the number of subwords."""
        total, count = np.zeros(self.size + 1), np.zeros(self.size + 1, np.int64)
        for place, bucket in self.layers:
            # places are distinct within a layer
            total[place + 1] += values[bucket]
            count[place + 1] += 1
        return np.cumsum(total), np.cumsum(count)


def _repeats(chunk: Chunk, h: np.ndarray, within: int) -> np.ndarray:
    """Which words equal one of the words before them in their text, at most within words back."""
    order = np.lexsort((np.arange(len(h)), h, chunk.doc))
    same = (h[order][1:] == h[order][:-1]) & (np.diff(chunk.doc[order]) == 0) & (np.diff(order) <= within)
    out = np.zeros(len(h), bool)
    out[order[1:][same]] = True
    return out


def places(chunk: Chunk, sizes: tuple[int, ...] = (3, 4, 5), bits: int = BITS, lower: bool = True, once_in: int = 0) -> Places:
    """The subwords of a chunk's words: n-grams of the given sizes, edges of words included, and the words.

    With once_in, a word that came up in as many words before in its text adds nothing.
    """
    shift = np.uint64(64 - bits)
    lens = np.diff(chunk.off)
    add = np.repeat(np.arange(chunk.n), lens) + 1
    at = np.arange(len(chunk.cp)) + add
    size = len(chunk.cp) + chunk.n + 1
    padded = np.full(size, 32, np.uint64)
    solid = np.zeros(size, bool)
    solid[at] = chunk.solid
    padded[at] = np.where(chunk.solid, chunk.lower if lower else chunk.cp, 32)
    shown = (padded + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    shown ^= shown >> np.uint64(31)
    layers = []
    for n in sizes:
        if size < n:
            continue
        inner = solid[1 : size - n + 2].copy()
        for k in range(2, n - 1):
            inner &= solid[k : size - n + 1 + k]
        place = np.flatnonzero(inner[: size - n + 1])
        h = np.full(len(place), n, np.uint64) * np.uint64(0x632BE59BD9B4E019)
        p = powers(n)
        for k in range(n):
            h += shown[place + k] * p[k]
        layers.append((place, (mix(h) >> shift).astype(np.int64)))
    shifted = add[chunk.starts] if len(chunk.starts) else np.zeros(0, np.int64)
    starts, ends = chunk.starts + shifted, chunk.ends + shifted
    h = chunk.hashes(lower)
    layers.append((starts, (mix(h.copy()) >> shift).astype(np.int64)))
    if once_in and len(h):
        again = _repeats(chunk, h, once_in)
        edge = np.zeros(size + 1, np.int8)
        edge[starts[again] - 1] += 1
        np.subtract.at(edge, ends[again], 1)
        heard = np.cumsum(edge) == 0
        layers = [(place[heard[place]], bucket[heard[place]]) for place, bucket in layers]
    return Places(size, layers, starts, ends)


def passages(chunk: Chunk, size: int, step: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, first word and end word of passages of size words, step words apart; the last one reaches the text's end.

    A text of size words or fewer is one passage; one without words is an empty passage.
    """
    n = chunk.n_words
    count = np.maximum(1, -(-(n - size) // step) + 1)
    doc = np.repeat(np.arange(chunk.n), count)
    k = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
    first = chunk.word_off[doc] + k * step
    return doc, first, np.minimum(first + size, chunk.word_off[doc + 1])


def edges(p: Places, first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The places from the first to before the end of runs of words, with the blanks at either side."""
    some = end > first
    a, b = np.zeros(len(first), np.int64), np.zeros(len(first), np.int64)
    a[some] = p.starts[first[some]] - 1
    b[some] = p.ends[end[some] - 1]
    return a, b


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int) -> tuple[list[str], np.ndarray]:
    """Whole texts and labels of at most per_class labelled documents a class, in the order of a hash of their id.

    The bound is what the driver holds; the hash chooses evenly over all labelled rows. Where ids repeat, the
    smallest label and any of the texts count.
    """
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).groupBy("doc_id").agg(F.min(label).alias("y"))
    classes = sorted(r.y for r in known.select("y").distinct().collect())
    chosen = None
    for y in classes:
        part = known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        chosen = part if chosen is None else chosen.unionAll(part)
    if chosen is None:
        return [], np.zeros(0, np.int64)
    ids = [(int(r.doc_id), int(r.y)) for r in chosen.collect()]
    picked = docs.sparkSession.createDataFrame(ids, "doc_id bigint, y int")
    got = has_columns(docs, "doc_id", "text").join(F.broadcast(picked), "doc_id").toArrow().sort_by([("doc_id", "ascending")])
    seen, texts, y = set(), [], []
    for i, t, v in zip(*(got[c].to_pylist() for c in ("doc_id", "text", "y")), strict=True):
        if i not in seen:
            seen.add(i)
            texts.append(t or "")
            y.append(v)
    return texts, np.array(y, np.int64)


def chunks_of(texts: list[str]):
    """Chunks of a list of texts."""
    return column_chunks(pa.array(texts, pa.large_string()))
