"""Linear maps before quantization: principal components, random rotations, learned rotations."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.operators.model import CodeModel, LinearMap
from twoview.operators.vectors import doubles, matrix


def moments(df: DataFrame, dims: int) -> tuple[int, np.ndarray, np.ndarray]:
    """Count, sum and sum of outer products; each batch sends dims * (dims + 1) numbers, Spark adds them up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dims + 1, dims + 1))
        for batch in batches:
            x = np.column_stack([np.ones(batch.num_rows), matrix(batch.column(0), dims)])
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size, dtype=np.int32)), pa.array(total.ravel())], names=["at", "v"])

    got = df.select(doubles().alias("embedding")).mapInArrow(run, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).toArrow()
    full = np.zeros((dims + 1) ** 2)
    full[got["at"].to_numpy()] = got["v"].to_numpy()
    full = full.reshape(dims + 1, -1)
    return int(full[0, 0]), full[0, 1:], full[1:, 1:]


def gram_sql(df: DataFrame) -> DataFrame:
    """The same sums (i, j, v) for i <= j by plain aggregation."""
    a = df.select("vec_id", F.posexplode(doubles()).alias("i", "x"))
    b = df.select("vec_id", F.posexplode(doubles()).alias("j", "y"))
    return a.join(b, "vec_id").where("i <= j").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def fit_pca(df: DataFrame, dims: int, k: int) -> LinearMap:
    """The k directions of the greatest variance, each with its largest component positive."""
    n, s, g = moments(df, dims)
    mean = s / max(n, 1)
    values, vectors = np.linalg.eigh(g / max(n, 1) - np.outer(mean, mean))
    top = vectors[:, np.argsort(-values, kind="stable")[:k]]
    top = top * np.sign(top[np.abs(top).argmax(0), np.arange(top.shape[1])])
    return LinearMap(top, mean)


def random_rotation(dims: int, seed: int = 0) -> LinearMap:
    """An orthogonal matrix drawn evenly."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dims, dims)))
    return LinearMap(q * np.sign(np.diag(r)), np.zeros(dims))


def balanced_rotation(df: DataFrame, dims: int, M: int, out_dim: int) -> LinearMap:
    """Principal directions dealt to M slices so that the products of their variances come out alike."""
    n, s, g = moments(df, dims)
    mean = s / max(n, 1)
    values, vectors = np.linalg.eigh(g / max(n, 1) - np.outer(mean, mean))
    order = np.argsort(-values)[:out_dim]
    room, load, parts = out_dim // M, np.zeros(M), [[] for _ in range(M)]
    for i in order:
        free = [m for m in range(M) if len(parts[m]) < room]
        m = min(free, key=lambda m: (load[m], m))
        parts[m].append(i)
        load[m] += np.log(max(values[i], 1e-12))
    return LinearMap(vectors[:, [i for p in parts for i in p]], mean)


def fit_rotation_pq(df: DataFrame, dims: int, M: int, b: int, out_dim: int, iters: int = 5, mode: str = "alternating", seed: int = 0) -> CodeModel:
    """Rotation with reduction and quantizer together: encode, then turn the vectors towards their decoded forms."""
    from twoview.operators.quantize import train_pq

    rotation = balanced_rotation(df, dims, M, out_dim)
    model = None
    for _ in range(iters if mode == "alternating" else 0):
        model = train_pq(df, M, b, dims=out_dim, seed=seed, iters=8, before=rotation)
        sent = df.sparkSession.sparkContext.broadcast(model)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            total = np.zeros((dims, out_dim))
            for batch in batches:
                x = matrix(batch.column(0), dims)
                total += (x - sent.value.before.mean).T @ sent.value.decode(sent.value.encode(x))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size, dtype=np.int32)), pa.array(total.ravel())], names=["at", "v"])

        got = df.select(doubles().alias("embedding")).mapInArrow(run, "at int, v double").groupBy("at").agg(F.sum("v").alias("v")).toArrow()
        cross = np.zeros(dims * out_dim)
        cross[got["at"].to_numpy()] = got["v"].to_numpy()
        u, _, vt = np.linalg.svd(cross.reshape(dims, out_dim), full_matrices=False)
        rotation = LinearMap(u @ vt, rotation.mean)
    return train_pq(df, M, b, dims=out_dim, seed=seed, before=rotation)
