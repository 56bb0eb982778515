"""Packing: buckets of text length with the least padding, and batches within a token budget.

Spark counts all documents by length; dynamic programming over that histogram chooses the upper bounds of a
given number of buckets that need the fewest padding tokens. Within a bucket rows are numbered in order, and
each batch takes as many as the budget holds at the bucket's bound.

The histogram has one entry for each length that occurs, at every size of the input: it grows with the variety of lengths, not
with the rows. The best last cut moves up with the length (cost has the quadrangle inequality), so that halving finds all of a round's
in n log n steps.

Cases: null and empty texts have the end token alone, length 1. Equal ids follow each other in any order. Texts longer than the budget
get batches of their own. An empty table gives an empty result. Other columns are left out of account.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import map_chunks, ranked, written


def best_bounds(length: np.ndarray, count: np.ndarray, total: np.ndarray, buckets: int) -> tuple[list[int], int]:
    """Upper bounds of at most so many buckets with the least padding, and that padding.

    length: ascending entries; count, total: rows and true tokens of each. Entries i + 1 to j in one bucket cost what they need at
    j's bound. Sums are of whole numbers, exact up to 2**53.
    """
    n = len(length)
    c, t = np.append(0, np.cumsum(count)).astype(float), np.append(0, np.cumsum(total)).astype(float)
    best = np.full(n + 1, np.inf)
    best[0] = 0
    came = []
    for _ in range(min(buckets, n)):
        new, back = np.full(n + 1, np.inf), np.zeros(n + 1, np.int64)
        new[0] = 0
        todo = [(1, n, 0, n - 1)]
        while todo:
            a, b, lo, hi = todo.pop()
            if a > b:
                continue
            j = (a + b) // 2
            top = min(hi, j - 1) + 1
            cost = best[lo:top] + length[j - 1] * (c[j] - c[lo:top]) - (t[j] - t[lo:top])
            at = lo + int(np.argmin(cost))
            back[j], new[j] = at, cost[at - lo]
            todo += [(a, j - 1, lo, at if np.isfinite(new[j]) else hi), (j + 1, b, at if np.isfinite(new[j]) else lo, hi)]
        best = new
        came.append(back)
    bounds, j = [], n
    for back in reversed(came):
        if j:
            bounds.append(int(length[j - 1]))
            j = int(back[j])
    return bounds[::-1], int(round(best[n]))


def pack(lengths: DataFrame, *, buckets: int = 16, budget: int = 16_384, order: str = "doc_id") -> DataFrame:
    """Batches of rows (doc_id, n_tokens and an order column): adds bucket, pad_to, batch (within the bucket), place.

    The bounds are the best for all rows. A batch at bound b holds max(1, budget // b) rows.
    """
    hist = lengths.groupBy(F.col("n_tokens").alias("length")).agg(F.count("*").alias("n")).toArrow().sort_by("length")  # a row a length that occurs
    if not hist.num_rows:
        return lengths.select("doc_id", "n_tokens").withColumns({c: F.lit(0).cast(k) for c, k in (("bucket", "int"), ("pad_to", "bigint"), ("batch", "bigint"), ("place", "int"))})
    length, n = hist["length"].to_numpy(), hist["n"].to_numpy()
    bounds, _ = best_bounds(length, n, n * length, buckets)
    which = F.lit(len(bounds) - 1)
    for k in range(len(bounds) - 2, -1, -1):
        which = F.when(F.col("n_tokens") <= bounds[k], k).otherwise(which)
    pad = F.element_at(F.array(*[F.lit(b).cast("bigint") for b in bounds]), F.col("bucket") + 1)
    cut = lengths.withColumn("bucket", which.cast("int")).withColumn("pad_to", pad)
    held = F.greatest(F.lit(1), F.floor(F.lit(budget) / F.col("pad_to")))
    numbered = ranked(cut, ["bucket"], order, "_rank").withColumns({"batch": F.floor(F.col("_rank") / held), "place": (F.col("_rank") % held).cast("int")})
    return numbered.select("doc_id", "n_tokens", "bucket", "pad_to", "batch", "place")


def pack_documents(docs: DataFrame, *, buckets: int = 16, budget: int = 16_384, order: str = "doc_id") -> DataFrame:
    """Pack documents (doc_id, text and an order column) by their number of words and an end token."""
    keep = ["doc_id"] if order == "doc_id" else ["doc_id", order]
    lengths = written(map_chunks(docs, "text", keep, lambda c: {"n_tokens": c.n_words + 1}, "n_tokens bigint"), "lengths")
    return pack(lengths, buckets=buckets, budget=budget, order=order)
