"""Product quantizers: training by several engines, encoding, decoding, errors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twoview.functions.expressions import l2sq
from twoview.operators.model import CodeModel, LinearMap, ModelSpec, pack_words
from twoview.operators.vectors import collect_matrix, doubles, lists, map_vectors, matrix, subvectors


def kmeans(x: np.ndarray, k: int, *, iters: int = 25, seed: int = 0, init: str = "random") -> np.ndarray:
    """Centroids of the rows of x. An empty cluster moves to the row farthest from its own centroid.

    init: 'first' rows, 'random' distinct rows, or 'pp' (far ones likelier).
    """
    if len(x) < k:
        raise ValueError(f"{k} centroids need at least {k} training rows, not {len(x)}; lower b or add rows")
    rng = np.random.default_rng(seed)
    if init == "first":
        c = x[:k].copy()
    elif init == "random":
        c = x[rng.choice(len(x), k, replace=False)].copy()
    else:
        c = [x[rng.integers(len(x))]]
        d = ((x - c[0]) ** 2).sum(1)
        for _ in range(k - 1):
            c.append(x[rng.choice(len(x), p=d / d.sum()) if d.sum() > 0 else rng.integers(len(x))])
            d = np.minimum(d, ((x - c[-1]) ** 2).sum(1))
        c = np.array(c)
    for _ in range(iters):
        near, d = _nearest(x, c)
        n = np.bincount(near, minlength=k)
        sums = np.stack([np.bincount(near, x[:, j], k) for j in range(x.shape[1])], 1)
        new = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
        empty = np.flatnonzero(n == 0)
        if len(empty):
            own = d + (x * x).sum(1)
            new[empty] = x[np.argsort(-own, kind="stable")[: len(empty)]]
        if np.array_equal(new, c):
            break
        c = new
    return c


def _nearest(x: np.ndarray, c: np.ndarray, rows: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """Each row's nearest centroid, and its squared distance less the row's own square; some rows at a time."""
    near, least, c2 = np.empty(len(x), np.int64), np.empty(len(x)), (c * c).sum(1)[None]
    for a in range(0, len(x), rows):
        d = c2 - 2 * x[a : a + rows] @ c.T
        near[a : a + rows] = i = d.argmin(1)
        least[a : a + rows] = d[np.arange(len(d)), i]
    return near, least


def train_pq(
    train: DataFrame, M: int, b: int, *, dims: int, iters: int = 25, seed: int = 0, init: str = "random", engine: str = "driver", before: LinearMap | None = None, max_rows: int = 100_000
) -> CodeModel:
    """A quantizer for each of M slices.

    engine 'driver': on a bounded sample; 'grouped': one task a slice; 'distributed': all rows, rounds of partial sums.
    """
    spec = ModelSpec(dims, M, b)
    spark = train.sparkSession
    if engine == "distributed":
        start = train_pq(train, M, b, dims=dims, iters=0, seed=seed, init=init, before=before, max_rows=max(max_rows, 4 * spec.K))
        return lloyd_distributed(train, start, iters)
    ids, x = collect_matrix(train, max_rows)
    blank = CodeModel(spec, np.zeros((M, spec.K, spec.ds)), None, before)
    s = blank.slices(x)
    if engine == "grouped":
        sent = spark.sparkContext.broadcast(s)
        K = spec.K

        def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
            m = int(key[0])
            return pd.DataFrame({"m": [m], "c": [kmeans(sent.value[m], K, iters=iters, seed=seed + m, init=init).ravel().tolist()]})

        got = spark.range(M).select(F.col("id").cast("int").alias("m")).groupBy("m").applyInPandas(run, "m int, c array<double>").toPandas().sort_values("m")
        book = np.stack([np.array(c).reshape(K, -1) for c in got["c"]])
    else:
        book = np.stack([kmeans(s[m], spec.K, iters=iters, seed=seed + m, init=init) for m in range(M)])
    return CodeModel(spec, book, None, before)


def lloyd_distributed(df: DataFrame, model: CodeModel, iters: int) -> CodeModel:
    """Rounds over all rows: each task adds up its rows by nearest centroid, M * K * (ds + 1) numbers reach the driver."""
    spec = model.spec
    for _ in range(iters):
        sent = df.sparkSession.sparkContext.broadcast(model)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            total = np.zeros((spec.M, spec.K, spec.ds + 1))
            for batch in batches:
                x = matrix(batch.column(0))
                if len(x):
                    codes, s = sent.value.encode(x), sent.value.slices(x)
                    for m in range(spec.M):
                        np.add.at(total[m], codes[:, m], np.column_stack([s[m], np.ones(len(x))]))
            some = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total.ravel()[some])], names=["at", "v"])

        got = df.select(doubles().alias("embedding")).mapInArrow(run, "at bigint, v double").groupBy("at").agg(F.sum("v").alias("v")).toArrow()
        total = np.zeros(spec.M * spec.K * (spec.ds + 1))
        total[got["at"].to_numpy()] = got["v"].to_numpy()
        total = total.reshape(spec.M, spec.K, -1)
        n = total[..., -1:]
        model = CodeModel(spec, np.where(n > 0, total[..., :-1] / np.maximum(n, 1), model.codebook), None, model.before)
    return model


def codebook_frame(spark: SparkSession, model: CodeModel) -> DataFrame:
    """The codebook as rows (m, i, centroid)."""
    rows = [(m, i, model.codebook[m, i].tolist()) for m in range(model.spec.M) for i in range(model.spec.K)]
    return spark.createDataFrame(rows, "m int, i int, centroid array<double>")


def codebook_first(train: DataFrame, spec: ModelSpec) -> DataFrame:
    """A codebook without training: slices of the K rows of the lowest ids. K rows reach one task by a top-k, no more."""
    lowest = train.select("vec_id", doubles().alias("embedding")).orderBy("vec_id").limit(spec.K)
    numbered = lowest.withColumn("i", F.row_number().over(Window.orderBy("vec_id")) - 1)
    cut = F.array(*[F.slice("embedding", m * spec.ds + 1, spec.ds) for m in range(spec.M)])
    return numbered.select("i", F.posexplode(cut).alias("m", "centroid")).select("m", "i", "centroid")


def encode_sql(df: DataFrame, codebook: DataFrame, spec: ModelSpec) -> DataFrame:
    """Nearest centroid of each slice as rows (vec_id, m, i, d2): a broadcast join on the slice and a minimum."""
    sub = subvectors(df, spec.M, spec.D)
    d2 = l2sq(F.col("sub"), F.col("centroid"))
    best = F.min(F.struct(d2.alias("d2"), "i")).alias("best")
    return sub.join(F.broadcast(codebook), "m").groupBy("vec_id", "m").agg(best).select("vec_id", "m", "best.i", "best.d2")


def lloyd_round_sql(train: DataFrame, codebook: DataFrame, spec: ModelSpec) -> DataFrame:
    """One round of k-means in plain SQL operators; a centroid without rows stays."""
    near = encode_sql(train, codebook, spec).select("vec_id", "m", "i")
    values = subvectors(train, spec.M, spec.D).join(near, ["vec_id", "m"]).select("m", "i", F.posexplode("sub").alias("d", "x"))
    means = values.groupBy("m", "i", "d").agg(F.avg("x").alias("x")).groupBy("m", "i").agg(F.sort_array(F.collect_list(F.struct("d", "x"))).alias("s"))
    moved = means.select("m", "i", F.col("s.x").alias("moved"))
    return codebook.join(moved, ["m", "i"], "left").select("m", "i", F.coalesce("moved", "centroid").alias("centroid"))


def model_of_frame(codebook: DataFrame, spec: ModelSpec) -> CodeModel:
    """A model from codebook rows; they are M * K."""
    rows = codebook.orderBy("m", "i").toArrow()
    return CodeModel(spec, matrix(rows["centroid"]).reshape(spec.M, spec.K, spec.ds))


def encode(df: DataFrame, model: CodeModel, keep: list[str] | None = None, numbers: bool = False) -> DataFrame:
    """Codes as words w0, w1, ... (and codes, the numbers themselves)."""
    sent = df.sparkSession.sparkContext.broadcast(model)
    spec = model.spec

    def one(x: np.ndarray) -> dict[str, np.ndarray]:
        codes = sent.value.encode(x) if len(x) else np.zeros((0, spec.M), np.int64)
        words = pack_words(codes, spec)
        return ({"codes": codes} if numbers else {}) | {f"w{i}": words[:, i] for i in range(spec.n_words)}

    schema = ("codes array<bigint>, " if numbers else "") + ", ".join(f"w{i} bigint" for i in range(spec.n_words))
    return map_vectors(df, one, schema, keep)


def decode(codes: DataFrame, model: CodeModel) -> DataFrame:
    """Reconstructed vectors (vec_id, embedding) of rows (vec_id, codes), by look-up in the codebook, sent once."""
    sent, spec = codes.sparkSession.sparkContext.broadcast(model), model.spec

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                numbers = matrix(batch.column(1)).astype(np.int64).reshape(-1, spec.M)
                yield pa.RecordBatch.from_arrays([batch.column(0), lists(sent.value.decode(numbers))], names=["vec_id", "embedding"])

    return codes.select("vec_id", "codes").mapInArrow(run, "vec_id bigint, embedding array<double>")


def reconstruction_error(df: DataFrame, model: CodeModel) -> DataFrame:
    """Mean squared error of each slice (m, mse) over all rows."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def one(x: np.ndarray) -> dict[str, np.ndarray]:
        m = sent.value
        d = m.slices(x) - np.stack([m.codebook[k][m.encode(x)[:, k]] for k in range(m.spec.M)])
        return {"err": np.einsum("mnd,mnd->nm", d, d)}

    errs = map_vectors(df, one, "err array<double>")
    return errs.select(F.posexplode("err").alias("m", "e")).groupBy("m").agg(F.avg("e").alias("mse"))


def fit_codes(train: DataFrame, dims: int, M: int, b: int, construction: str = "plain", *, seed: int = 0, alpha: float = 0.5, n_iter: int = 500_000, restarts: int = 1, rotation_dim: int | None = None, engine: str = "driver") -> CodeModel:
    """A model by its construction: 'plain', 'dist_assigned' or 'rank_assigned', on a learned rotation if rotation_dim is given."""
    from twoview.operators.assignment import fit_assignment
    from twoview.operators.linear import fit_rotation_pq

    model = fit_rotation_pq(train, dims, M, b, rotation_dim, seed=seed) if rotation_dim else train_pq(train, M, b, dims=dims, seed=seed, engine=engine)
    if construction == "plain":
        return model
    return fit_assignment(train.sparkSession, model, construction, alpha=alpha, n_iter=n_iter, restarts=restarts, seed=seed)[0]
