"""Vectors in DataFrames: splits, checks, scaling, slices, and Arrow batches as matrices."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from twoview.operators.model import LinearMap


@dataclass
class Split:
    """Three disjoint sets of one source."""

    train: DataFrame
    base: DataFrame
    query: DataFrame


def split(df: DataFrame, id_col: str = "vec_id", mod: int = 10) -> Split:
    """By the id's remainder: 0 queries, 1 to 3 training, the rest the base that is searched."""
    r = F.pmod(F.col(id_col), F.lit(mod))
    return Split(df.where((r >= 1) & (r <= 3)), df.where(r >= 4), df.where(r == 0))


def validate(df: DataFrame, dims: int) -> tuple[DataFrame, DataFrame]:
    """Sound vectors, and the others with a reason."""
    e = F.col("embedding")
    reason = (
        F.when(e.isNull(), "null vector")
        .when(F.size(e) != dims, "wrong length")
        .when(F.exists(e, lambda x: x.isNull()), "null component")
        .when(F.exists(e, lambda x: F.isnan(x) | (F.abs(x) == float("inf"))), "not finite")
    )
    tagged = df.withColumn("reason", reason)
    return tagged.where("reason IS NULL").drop("reason"), tagged.where("reason IS NOT NULL")


def doubles(column: str = "embedding") -> Column:
    return F.col(column).cast("array<double>")


def l2_normalize(df: DataFrame) -> DataFrame:
    """Vectors of length one; zero vectors stay."""
    norm = F.sqrt(F.aggregate(doubles(), F.lit(0.0), lambda s, v: s + v * v))
    return df.withColumn("_n", norm).withColumn("embedding", F.when(F.col("_n") > 0, F.transform(doubles(), lambda v: v / F.col("_n"))).otherwise(doubles())).drop("_n")


def standardize(df: DataFrame, columns: list[str], out: str = "embedding") -> DataFrame:
    """Z-scores of numeric columns as a vector; one aggregation, whose single row is sent to all."""
    stats = df.agg(*[f for c in columns for f in (F.avg(c).alias(f"_m_{c}"), F.stddev_pop(c).alias(f"_s_{c}"))])
    score = [F.when(F.col(f"_s_{c}") > 0, (F.col(c) - F.col(f"_m_{c}")) / F.col(f"_s_{c}")).otherwise(0.0) for c in columns]
    return df.crossJoin(F.broadcast(stats)).withColumn(out, F.array(*score)).drop(*[f"_{k}_{c}" for c in columns for k in "ms"])


def subvectors(df: DataFrame, M: int, dims: int, layout: str = "long") -> DataFrame:
    """Slices of each vector: long (vec_id, m, sub), or wide columns s0, s1, ..."""
    ds = dims // M
    cut = [F.slice(doubles(), m * ds + 1, ds) for m in range(M)]
    if layout == "wide":
        return df.select("vec_id", *[c.alias(f"s{m}") for m, c in enumerate(cut)])
    return df.select("vec_id", F.posexplode(F.array(*cut)).alias("m", "sub"))


def matrix(column: pa.Array | pa.ChunkedArray, width: int | None = None) -> np.ndarray:
    """A list column as a matrix of doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros((0, width or 0))
    off = column.offsets.to_numpy()
    return column.values.to_numpy(zero_copy_only=False)[off[0] : off[-1]].reshape(len(column), -1).astype(np.float64)


def lists(x: np.ndarray) -> pa.Array:
    """A matrix as a list column."""
    kind = pa.float64() if x.dtype.kind == "f" else pa.int64()
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(np.ascontiguousarray(x).ravel(), kind))


def map_vectors(df: DataFrame, fn: Callable[[np.ndarray], dict[str, np.ndarray]], schema: str, keep: list[str] | None = None, rows: int = 1 << 30) -> DataFrame:
    """Kept columns and what fn makes of a batch's vectors, one row in for one row out; at most rows rows at a time."""
    keep = keep or ["vec_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(a, rows) for whole in batches for a in range(0, max(whole.num_rows, 1), rows)):
            made = fn(matrix(batch.column(len(keep))))
            if batch.num_rows:
                arrays = [lists(v) if v.ndim == 2 else pa.array(v) for v in made.values()]
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *arrays], names=[*keep, *made])

    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(*keep, doubles().alias("embedding")).mapInArrow(run, f"{kinds}, {schema}")


def apply_map(df: DataFrame, linear: LinearMap, engine: str = "arrow") -> DataFrame:
    """Vectors through a linear map: BLAS on Arrow batches, or plain expressions ('sql') for small maps."""
    if engine == "arrow":
        sent = df.sparkSession.sparkContext.broadcast(linear)
        return map_vectors(df, lambda x: {"embedding": sent.value.apply(x)}, "embedding array<double>")
    shifted = F.zip_with(doubles(), F.array(*[F.lit(float(v)) for v in linear.mean]), lambda a, b: a - b)
    rows = F.array(*[F.array(*[F.lit(float(v)) for v in col]) for col in linear.matrix.T])
    out = F.transform(rows, lambda r: F.aggregate(F.zip_with(r, F.col("_x"), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v))
    return df.withColumn("_x", shifted).select("vec_id", out.alias("embedding"))


def collect_matrix(df: DataFrame, limit: int = 200_000) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors, ascending by id, of all rows or of limit rows where there are more: those of the least hashes of their ids.

    For training sets of a bounded size. A hash threshold, from the count, comes before the sort, so that about a
    tenth more than limit rows are sorted.
    """
    rows = df.select("vec_id", doubles().alias("embedding"))
    n = df.count()
    if n > limit:
        share = min(1.0, (1.1 * limit + 100) / n)
        h = F.xxhash64("vec_id")
        rows = rows.where(F.pmod(h, F.lit(1 << 30)) < int(share * (1 << 30))).orderBy(F.pmod(h, F.lit(1 << 30)), "vec_id").limit(limit)
    got = rows.toArrow().sort_by("vec_id")
    return got["vec_id"].to_numpy(), matrix(got["embedding"])


def lowest_ids(df: DataFrame, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """The rows of the lowest ids, ascending."""
    got = df.select("vec_id", doubles().alias("embedding")).orderBy("vec_id").limit(rows).toArrow()
    return got["vec_id"].to_numpy(), matrix(got["embedding"])


def training_sample(df: DataFrame, rows: int, total: int | None = None) -> DataFrame:
    """About rows rows chosen by a hash of the id, the same ones each time."""
    n = df.count() if total is None else total
    return df if n <= rows else df.where(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30)) < int(rows / n * (1 << 30)))


def stratified_sample(df: DataFrame, by: str, rows: int) -> DataFrame:
    """About rows rows of each value of a column, chosen by a hash of the id; all of those with fewer. Counts are one row a value."""
    counts = df.groupBy(F.col(by).alias("_by")).agg(F.count("*").alias("_n"))
    share = F.least(F.lit(1.0), F.lit(float(rows)) / F.col("_n"))
    near = F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30)) < share * (1 << 30)
    return df.join(F.broadcast(counts), F.col(by).eqNullSafe(F.col("_by"))).where(near).drop("_by", "_n")
