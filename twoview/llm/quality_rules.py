"""Quality rules judged by an isolation forest.

Rules measure each document; shares of those measures go to an isolation forest, in which a document that few
random splits set apart has a short mean path and so a high anomaly score. The score above which a document
goes is calibrated on the labelled rows.

Cases: a null or empty text has no words, fails the base rules and is not kept. Repeated rows are judged
alike, each by itself. Without labelled rows of both grades no score is high enough to reject. An empty
table gives an empty result. Other columns are left out of account.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import map_chunks, written
from twoview.llm.text import Chunk, column_chunks, span_hashes, windows

SYMBOLS = "#*$%&|<>"
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
WINDOW = 5
RULES = "n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, n_upper bigint, n_punct bigint, n_digits bigint"
#: Least and greatest ordinary share: characters a word, then shares of characters or words.
SOFT = {"mean_word": (3, 10), "symbols": (0, 0.02), "dup_lines": (0, 0.1), "repeats": (0, 0.2), "upper": (0, 0.3), "punct": (0, 0.1), "digits": (0, 0.5)}


def _among(cp: np.ndarray, chars: str) -> np.ndarray:
    """True where a code point is one of some ASCII characters."""
    lookup = np.zeros(129, bool)
    lookup[[ord(c) for c in chars]] = True
    return lookup[np.minimum(cp, 128)]


def _twice(doc: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For values h in texts doc: which occur twice or more in their text, and which are no first occurrence."""
    order = np.lexsort((np.arange(len(h)), h, doc))
    d, s = doc[order], h[order]
    same = np.zeros(len(h) + 1, bool)
    same[1:-1] = (s[1:] == s[:-1]) & (d[1:] == d[:-1])
    often, later = np.zeros(len(h), bool), np.zeros(len(h), bool)
    often[order] = same[:-1] | same[1:]
    later[order] = same[:-1]
    return often, later


def duplicate_lines(chunk: Chunk) -> np.ndarray:
    """Lines of each text that hold a word and equal an earlier line of it."""
    breaks = np.flatnonzero(chunk.cp == 10)
    filled = chunk.off[:-1][np.diff(chunk.off) > 0]
    starts = np.union1d(filled, breaks + 1)
    # a break at a text's end opens an empty line there, which the next text's first line stands for
    starts = starts[starts < len(chunk.cp)]
    if not len(starts):
        return np.zeros(chunk.n, np.int64)
    ends = np.append(starts[1:], len(chunk.cp))
    ends = ends - (chunk.cp[ends - 1] == 10)
    words = np.searchsorted(chunk.starts, ends) > np.searchsorted(chunk.starts, starts)
    starts, ends = starts[words], ends[words]
    h = _line_hashes(chunk, starts, ends)
    doc = np.searchsorted(chunk.off, starts, "right") - 1
    _, later = _twice(doc, h)
    return np.bincount(doc[later], minlength=chunk.n)


def _line_hashes(chunk: Chunk, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.zeros(0, np.uint64)
    edges = np.zeros(len(chunk.cp) + 1, np.int8)
    np.add.at(edges, starts, 1)
    np.add.at(edges, ends, -1)
    return span_hashes(chunk.cp, starts, ends, np.cumsum(edges[:-1]) > 0)


def repeated_words(chunk: Chunk, size: int = WINDOW) -> np.ndarray:
    """Words of each text that lie in a window of size words which the text holds twice or more."""
    h, at = windows(chunk, chunk.hashes(lower=False), size)
    if not len(h):
        return np.zeros(chunk.n, np.int64)
    often, _ = _twice(chunk.doc[at], h)
    cover = np.zeros(len(chunk.starts) + size + 1, np.int64)
    hits = at[often]
    np.add.at(cover, hits, 1)
    np.add.at(cover, hits + size, -1)
    covered = np.cumsum(cover)[: len(chunk.starts)] > 0
    return np.bincount(chunk.doc[covered], minlength=chunk.n)


def rule_counts(chunk: Chunk) -> dict[str, np.ndarray]:
    """The counts of RULES for each text."""
    lens = np.append(0, np.cumsum(chunk.ends - chunk.starts))
    cp = chunk.cp
    return {
        "n_words": chunk.n_words.astype(np.int64),
        "word_chars": lens[chunk.word_off[1:]] - lens[chunk.word_off[:-1]],
        "n_symbols": chunk.per_doc(_among(cp, SYMBOLS)),
        "n_dup_lines": duplicate_lines(chunk).astype(np.int64),
        "n_repeat_words": repeated_words(chunk).astype(np.int64),
        "n_upper": chunk.per_doc((cp - np.uint32(65)) < 26),
        "n_punct": chunk.per_doc(_among(cp, "!?;:=_{}[]()\"'/\\~^`@+-")),
        "n_digits": chunk.per_doc((cp - np.uint32(48)) < 10),
    }


def features(c: dict[str, np.ndarray]) -> np.ndarray:
    """By how much each rule's share goes beyond its soft bound of SOFT, one row a text.

    Shares don't depend on a text's length. Ordinary texts lie within all bounds, at the origin, so that chance
    differences among them don't take up the forest's splits.
    """
    chars, words = np.maximum(c["word_chars"], 1).astype(float), np.maximum(c["n_words"], 1).astype(float)
    shares = {
        "mean_word": c["word_chars"] / words,
        "symbols": c["n_symbols"] / chars,
        "dup_lines": c["n_dup_lines"] / words,
        "repeats": c["n_repeat_words"] / words,
        "upper": c["n_upper"] / chars,
        "punct": c["n_punct"] / chars,
        "digits": c["n_digits"] / chars,
    }
    return np.stack([np.maximum(shares[k] - high, 0) + np.maximum(low - shares[k], 0) for k, (low, high) in SOFT.items()], axis=1)


@dataclass
class IsolationForest:
    """Trees as flat arrays; a leaf has feature -1 and its depth, plus what a full tree would add, as its path."""

    feature: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    path: np.ndarray
    norm: float
    depth: int

    def score(self, x: np.ndarray) -> np.ndarray:
        """Anomaly score of each row, from 0 to 1; short paths score high."""
        total = np.zeros(len(x))
        rows = np.arange(len(x))
        for t in range(self.feature.shape[0]):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                f = self.feature[t][node]
                right = x[rows, np.maximum(f, 0)] >= self.cut[t][node]
                node = np.where(f < 0, node, self.left[t][node] + right)
            total += self.path[t][node]
        return np.exp2(-total / self.feature.shape[0] / self.norm)


def _expected_path(n: int) -> float:
    """Mean path of an unsuccessful search in a binary tree of n keys."""
    return 0.0 if n < 2 else 1.0 if n == 2 else 2 * (np.log(n - 1) + np.euler_gamma) - 2 * (n - 1) / n


def fit_forest(x: np.ndarray, trees: int = 100, sample: int = 256, seed: int = 7) -> IsolationForest:
    """An isolation forest: each tree splits its own sample of rows at random features and cuts."""
    rng = np.random.default_rng(seed)
    take = min(sample, len(x))
    depth = max(1, int(np.ceil(np.log2(max(take, 2)))))
    size = 2 ** (depth + 1)
    feature, cut = np.full((trees, size), -1, np.int64), np.zeros((trees, size))
    left, path = np.zeros((trees, size), np.int64), np.zeros((trees, size))
    for t in range(trees):
        used, todo = 1, [(0, x[rng.choice(len(x), take, replace=False)], 0)]
        while todo:
            node, part, d = todo.pop()
            varied = np.flatnonzero(part.max(0) > part.min(0)) if len(part) > 1 else []
            if d == depth or not len(varied):
                path[t, node] = d + _expected_path(len(part))
                continue
            f = int(rng.choice(varied))
            at = rng.uniform(part[:, f].min(), part[:, f].max())
            high = part[:, f] >= at
            feature[t, node], cut[t, node], left[t, node] = f, at, used
            todo += [(used, part[~high], d + 1), (used + 1, part[high], d + 1)]
            used += 2
    return IsolationForest(feature, cut, left, path, max(_expected_path(take), 1.0), depth)


def calibrate(bins: list[tuple[int, int, int]], n_bins: int, max_clean_loss: float) -> float:
    """The score from which documents go, of (bin, good rows, bad rows).

    At most a share of max_clean_loss of the good labelled rows lies above it; of the scores that allow this it is
    halfway from the lowest to the lowest bad row's there. Without good or bad rows it is over 1, which keeps all.
    """
    good, bad = np.zeros(n_bins + 1, np.int64), np.zeros(n_bins + 1, np.int64)
    for b, g, w in bins:
        good[b], bad[b] = g, w
    lost = np.cumsum(good[::-1])[::-1]
    allowed = np.flatnonzero(lost <= max_clean_loss * good.sum())
    if not good.sum() or not bad.sum() or not len(allowed):
        return 2.0
    caught = np.flatnonzero(bad[allowed[0] :])
    return float(allowed[0] + caught[0] // 2) / n_bins if len(caught) else 2.0


@dataclass
class Judge:
    """A forest and the score from which documents go; judges texts by themselves."""

    forest: IsolationForest | None
    threshold: float

    def scores(self, counts: dict[str, np.ndarray]) -> np.ndarray:
        n = len(counts["n_words"])
        return self.forest.score(features(counts)) if self.forest is not None and n else np.zeros(n)

    def keeps(self, chunk: Chunk) -> np.ndarray:
        counts = rule_counts(chunk)
        return ~base_failed(counts["n_words"], counts["n_repeat_words"]) & (self.scores(counts) < self.threshold)


def base_failed(n_words, n_repeat_words):
    """The base rules, of arrays or columns."""
    return (n_words < MIN_WORDS) | (100 * n_repeat_words > MAX_REPEAT_PERCENT * n_words)


def _scored(stats: DataFrame, forest: IsolationForest | None) -> DataFrame:
    """stats with each row's score and base_failed."""
    names = [n.split()[0] for n in RULES.split(", ")]
    sent = stats.sparkSession.sparkContext.broadcast(Judge(forest, 0.0))

    def score(batches):
        for batch in batches:
            c = {n: batch.column(batch.schema.get_field_index(n)).to_numpy(zero_copy_only=False) for n in names}
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(sent.value.scores(c))], names=[*batch.schema.names, "score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stats.schema) + ", score double"
    return stats.mapInArrow(score, schema).withColumn("base_failed", base_failed(F.col("n_words"), F.col("n_repeat_words")))


def _fit(stats: DataFrame, labels: DataFrame, trees: int, sample: int, max_clean_loss: float, n_bins: int, seed: int) -> tuple[Judge, DataFrame]:
    """A judge from the rules' counts of all documents, and the scored counts.

    The sample is a hash threshold first, by a count of all rows, so that about twice its rows are sorted.
    """
    names = [n.split()[0] for n in RULES.split(", ")]
    bound = trees * sample
    order = F.xxhash64("doc_id", *names)
    share = min(1.0, 2.0 * bound / max(stats.count(), 1))
    near = stats.select("doc_id", *names, order.alias("_o")).where(F.pmod(F.xxhash64("_o"), F.lit(1 << 20)) <= int(share * (1 << 20)))
    picked = near.orderBy("_o").limit(bound).select(*names).toPandas()
    forest = fit_forest(features({n: picked[n].to_numpy() for n in names}), trees, sample, seed) if len(picked) else None
    scored = _scored(stats, forest)
    known = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    bins = (
        scored.where(~F.col("base_failed"))
        .join(known, "doc_id")
        .groupBy(F.floor(F.col("score") * n_bins).cast("int").alias("bin"))
        .agg(F.count_if(F.col("quality") > 0).alias("good"), F.count_if(F.col("quality") <= 0).alias("bad"))
    )
    return Judge(forest, calibrate([(r.bin, r.good, r.bad) for r in bins.collect()], n_bins, max_clean_loss)), scored


def quality_rules(
    docs: DataFrame, labels: DataFrame, *, trees: int = 100, sample: int = 256, max_clean_loss: float = 0.0005, n_bins: int = 4096, seed: int = 7
) -> DataFrame:
    """Judge documents (doc_id, text) by rules and an isolation forest; labels (doc_id, quality) calibrate it.

    The forest takes trees * sample rows at most, chosen by a hash over all documents, as its method defines; its
    threshold comes from a histogram of all labelled rows' scores. Returns doc_id, the rules' counts, base_failed,
    score, threshold, kept.
    """
    stats = written(map_chunks(docs, "text", ["doc_id"], rule_counts, RULES), "rules")
    judge, scored = _fit(stats, labels, trees, sample, max_clean_loss, n_bins, seed)
    return scored.withColumns({"threshold": F.lit(judge.threshold), "kept": ~F.col("base_failed") & (F.col("score") < F.lit(judge.threshold))})


def kept_documents(
    docs: DataFrame, labels: DataFrame, *, trees: int = 100, sample: int = 256, max_clean_loss: float = 0.0005, n_bins: int = 4096, seed: int = 7
) -> DataFrame:
    """The rows of docs, with all columns, that quality_rules keeps; every row is judged by its own text, whatever its id.

    Texts are read a second time and judged where they are, so that none goes through a shuffle.
    """
    stats = written(map_chunks(docs, "text", ["doc_id"], rule_counts, RULES), "rules")
    judge, _ = _fit(stats, labels, trees, sample, max_clean_loss, n_bins, seed)
    sent, at = docs.sparkSession.sparkContext.broadcast(judge), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            keep = [sent.value.keeps(chunk) for chunk in column_chunks(batch.column(at))]
            yield batch.filter(pa.array(np.concatenate(keep))) if keep else batch

    return docs.mapInArrow(run, docs.schema)
