"""Python functions for SQL: cell probing as a table function, top-k as an aggregate, encoding as a scalar function."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from twoview.operators.coarse import probe_order
from twoview.operators.model import CodeModel, pack_words


class ProbeCells:
    """The cells that a query visits, nearest first, from its distances to the centroids of either part."""

    def eval(self, d_u: list[float], d_v: list[float], n_probe: int) -> Iterator[tuple[int, int, float]]:
        for nth, (d, cell) in enumerate(probe_order([np.array(d_u), np.array(d_v)], n_probe)):
            yield cell, nth + 1, d


def topk_agg(k: int) -> Callable:
    """An aggregate (id, score) -> ids of the k lowest scores, for groups that fit a task; windows are the way for all others."""

    def lowest(ids: pd.Series, scores: pd.Series) -> list[int]:
        order = np.lexsort((ids.to_numpy(), scores.to_numpy()))[:k]
        return ids.to_numpy()[order].tolist()

    lowest.__annotations__ = {"ids": pd.Series, "scores": pd.Series, "return": list}
    return F.pandas_udf(lowest, "array<bigint>", functionType=F.PandasUDFType.GROUPED_AGG)


def encode_udf(spark: SparkSession, model: CodeModel) -> Callable:
    """A scalar function from a vector to its code's words."""
    sent = spark.sparkContext.broadcast(model)

    def words(vectors: pd.Series) -> pd.Series:
        m = sent.value
        return pd.Series(list(pack_words(m.encode(np.stack([np.asarray(v, float) for v in vectors])), m.spec))) if len(vectors) else pd.Series([], dtype=object)

    words.__annotations__ = {"vectors": pd.Series, "return": pd.Series}
    return F.pandas_udf(words, "array<bigint>")


def register(spark: SparkSession) -> None:
    """probe_cells(d_u, d_v, n_probe) as a table function of SQL."""
    spark.udtf.register("probe_cells", F.udtf(ProbeCells, returnType="cell bigint, ord int, cell_d2 double"))
