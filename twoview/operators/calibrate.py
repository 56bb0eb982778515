"""Choosing the bit threshold and the number of cells."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twoview.operators.model import CodeModel
from twoview.operators.search import query_chunks


#: Pairs of codes that a task counts at a time.
PAIRS = 1 << 20


def histogram(words: list[np.ndarray], asked: np.ndarray, bits: int) -> np.ndarray:
    """Pairs of words with all rows of asked by differing bits."""
    h = np.empty((len(asked), len(words[0])), np.uint8 if bits < 256 else np.uint16)
    for row, own in zip(h, asked, strict=True):
        row[:] = np.bitwise_count(words[0] ^ own[0])
        for w, x in zip(words[1:], own[1:], strict=True):
            row += np.bitwise_count(w ^ x)
    return np.bincount(h.ravel(), minlength=bits + 1)


def hamming_histogram(prepared: DataFrame, codes: DataFrame, model: CodeModel) -> DataFrame:
    """Pairs by Hamming distance: (h, n, kept, kept_share), at most one row a distance."""
    n, bits, parts = model.spec.n_words, model.spec.bits, []
    for chunk in query_chunks(prepared.select("qid", *[f"q{i}" for i in range(n)]), 64):
        got = chunk.toArrow()  # at most BROADCAST_BYTES
        sent = codes.sparkSession.sparkContext.broadcast(np.stack([got[f"q{i}"].to_numpy() for i in range(n)], 1).view(np.uint64))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            counts = np.zeros(bits + 1, np.int64)
            for batch in batches:
                words = [batch.column(i).to_numpy().view(np.uint64) for i in range(n)]
                rows = max(1, PAIRS // max(batch.num_rows, 1))
                for a in range(0, len(sent.value) if batch.num_rows else 0, rows):
                    counts += histogram(words, sent.value[a : a + rows], bits)
            some = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(counts[some])], names=["h", "n"])

        parts.append(codes.select(*[f"w{i}" for i in range(n)]).mapInArrow(run, "h int, n bigint"))
    hist = reduce(DataFrame.unionAll, parts).groupBy("h").agg(F.sum("n").alias("n"))
    upto = Window.orderBy("h").rowsBetween(Window.unboundedPreceding, 0)  # at most bits + 1 rows
    total = Window.partitionBy()
    return hist.withColumn("kept", F.sum("n").over(upto)).withColumn("kept_share", F.col("kept") / F.sum("n").over(total))


def calibrate_tau(prepared: DataFrame, codes: DataFrame, model: CodeModel, keep: float = 0.05) -> int:
    """The largest threshold that keeps no more than the given share of pairs; -1 if even equal codes are more."""
    row = hamming_histogram(prepared, codes, model).where(F.col("kept_share") <= keep).agg(F.max("h").alias("tau")).first()
    return -1 if row.tau is None else int(row.tau)


def pareto(points: DataFrame, cost: str, gain: str) -> DataFrame:
    """Marks points (cost, gain) that no cheaper or equally cheap point beats."""
    before = Window.orderBy(cost, F.desc(gain)).rowsBetween(Window.unboundedPreceding, -1)  # one row a setting
    best = F.max(gain).over(before)
    return points.withColumn("optimal", best.isNull() | (F.col(gain) > best))


def cheapest(points: DataFrame, cost: str, gain: str, target: float) -> DataFrame:
    """The cheapest point that reaches a target."""
    return points.where(F.col(gain) >= target).orderBy(cost, F.desc(gain)).limit(1)
