"""Reading and writing vectors, models and codes."""

from __future__ import annotations

import json
import struct
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from twoview.operators.model import CodeModel, LinearMap, ModelSpec


def save_model(spark: SparkSession, model: CodeModel, path: str) -> None:
    """One row: sizes and constants; small, so a single file."""
    row = {
        "spec": json.dumps({"D": model.spec.D, "M": model.spec.M, "b": model.spec.b, "tau": model.tau, "construction": model.construction}),
        "codebook": model.codebook.ravel().tolist(),
        "matrix": None if model.before is None else model.before.matrix.ravel().tolist(),
        "mean": None if model.before is None else model.before.mean.tolist(),
    }
    schema = "spec string, codebook array<double>, matrix array<double>, mean array<double>"
    spark.createDataFrame([row], schema).coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> CodeModel:
    row = spark.read.parquet(path).first()
    s = json.loads(row.spec)
    spec = ModelSpec(s["D"], s["M"], s["b"])
    before = None
    if row["matrix"] is not None:
        mean = np.array(row["mean"])
        before = LinearMap(np.array(row["matrix"]).reshape(len(mean), -1), mean)
    return CodeModel(spec, np.array(row.codebook).reshape(spec.M, spec.K, spec.ds), s["tau"], before, s["construction"])


def save_codes(codes: DataFrame, path: str, layout: str = "range", parts: int = 8, table: str | None = None) -> None:
    """Codes clustered by cell (or id), so that row groups' least and greatest cells prune scans.

    layout 'range': files of successive cells; 'partition': folders of cell_hi, at most parts of them; 'bucket': a bucketed table.
    """
    key = "cell" if "cell" in codes.columns else "vec_id"
    if layout == "range":
        codes.repartitionByRange(parts, key).sortWithinPartitions(key, "vec_id").write.mode("overwrite").parquet(path)
    elif layout == "partition":
        codes.withColumn("cell_hi", F.pmod(F.col(key), F.lit(parts))).repartition(parts, "cell_hi").sortWithinPartitions(key).write.mode("overwrite").partitionBy("cell_hi").parquet(path)
    elif layout == "bucket":
        codes.write.mode("overwrite").bucketBy(parts, key).sortBy(key).option("path", path).saveAsTable(table or "twoview_codes")
    else:
        raise ValueError(f"unknown layout {layout}")


def export_vectors(df: DataFrame, path: str, fmt: str) -> None:
    """JSON, ORC and Parquet keep arrays; CSV and text hold them as joined strings."""
    if fmt in ("json", "orc", "parquet"):
        df.select("vec_id", "embedding").write.mode("overwrite").format(fmt).save(path)
    else:
        line = df.select("vec_id", F.array_join(F.col("embedding").cast("array<string>"), " ").alias("v"))
        if fmt == "csv":
            line.write.mode("overwrite").csv(path)
        else:
            line.select(F.concat_ws("\t", F.col("vec_id").cast("string"), "v").alias("value")).write.mode("overwrite").text(path)


def import_vectors(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """What export_vectors wrote, as (vec_id, embedding array<double>)."""
    if fmt in ("json", "orc", "parquet"):
        return spark.read.schema("vec_id bigint, embedding array<double>").format(fmt).load(path)
    if fmt == "csv":
        raw = spark.read.schema("vec_id bigint, v string").csv(path)
    else:
        parts = F.split("value", "\t")
        raw = spark.read.text(path).select(parts[0].cast("bigint").alias("vec_id"), parts[1].alias("v"))
    return raw.select("vec_id", F.split("v", " ").cast("array<double>").alias("embedding"))


class VecsPart(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class VecsSource(DataSource):
    """Files of length-prefixed vectors (option dtype: float32, int32 or uint8), a folder or one file that tasks can open."""

    @classmethod
    def name(cls) -> str:
        return "vecs"

    def schema(self) -> str:
        return "vec_id bigint, embedding array<double>"

    def reader(self, schema) -> DataSourceReader:
        return VecsReader(self.options)


class VecsReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.dtype = options["path"], options.get("dtype", "float32")

    def partitions(self) -> list[InputPartition]:
        import os

        if os.path.isdir(self.path):
            return [VecsPart(os.path.join(self.path, f)) for f in sorted(os.listdir(self.path)) if not f.startswith((".", "_"))]
        return [VecsPart(self.path)]

    def read(self, partition: VecsPart) -> Iterator[tuple[int, list[float]]]:
        width = np.dtype(self.dtype).itemsize
        with open(partition.path, "rb") as f:
            at = 0
            while head := f.read(4):
                n = struct.unpack("<i", head)[0]
                yield at, np.frombuffer(f.read(n * width), self.dtype).astype(float).tolist()
                at += 1


def write_vecs(rows: np.ndarray, path: str, dtype: str = "float32") -> None:
    """A file of length-prefixed vectors, for exchange and tests."""
    with open(path, "wb") as f:
        for row in rows.astype(dtype):
            f.write(struct.pack("<i", len(row)) + row.tobytes())


def read_vecs_files(spark: SparkSession, path: str, dtype: str = "float32") -> DataFrame:
    """The same form read through Spark's own file access, one task a file; vec_id counts within a file."""
    files = spark.read.format("binaryFile").load(path).select("content")

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for blob in batch.column(0).to_pylist():
                n = struct.unpack("<i", blob[:4])[0]
                width = np.dtype(dtype).itemsize
                x = np.frombuffer(blob, np.dtype([("n", "<i4"), ("v", dtype, (n,))]) if width else None)["v"].astype(float)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.arange(len(x))), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * n, pa.int32()), pa.array(x.ravel()))], names=["vec_id", "embedding"]
                )

    return files.mapInArrow(run, "vec_id bigint, embedding array<double>")


def register_views(spark: SparkSession, codes: DataFrame, prepared: DataFrame) -> None:
    """Temp views codes and prepared_queries for SQL."""
    codes.createOrReplaceTempView("codes")
    prepared.createOrReplaceTempView("prepared_queries")
