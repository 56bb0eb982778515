"""What the operators share: reading tables, the shared folder, and mapping text columns."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import NumericType

from twoview.llm.text import Chunk, column_chunks


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; read by Spark alone, so that any store will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see, as the session names it; where none is set, a temporary one, on a single machine only."""
    context = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not path:
        if not re.fullmatch(r"local(\[[^\]]*\])?", context.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        path = tempfile.mkdtemp(prefix="twoview-")
        context.setCheckpointDir(path)
    return path


def written(df: DataFrame, name: str, **options: str) -> DataFrame:
    """df as a Parquet table in the shared folder: lineage ends there, and lost executors lose nothing of it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/twoview/{name}-{uuid.uuid4().hex}"
    df.write.options(**{"compression": "zstd"} | options).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written = path
    return out


def delete(*tables: DataFrame) -> None:
    """Removes tables that written made, once nothing will read them any more."""
    for df in tables:
        java = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(df._written)
        java.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(java, True)


def has_columns(df: DataFrame, *names: str) -> DataFrame:
    """df cut down to the named columns, so that other columns of any name can't clash."""
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df.select(*[F.col(f"`{n}`") for n in names])


def map_chunks(df: DataFrame, text_col: str, keep: list[str], fn: Callable[[Chunk], dict[str, object] | None], schema: str) -> DataFrame:
    """One row out for each row in: the kept columns, and those that fn makes of a chunk of texts.

    fn returns arrays by name, one value a text, in the order of the schema's columns after the kept ones.
    """
    source = has_columns(df, *keep, text_col)
    kinds = ", ".join(f"`{n}` {source.schema[n].dataType.simpleString()}" for n in keep)
    n_keep = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in column_chunks(batch.column(n_keep)):
                made = fn(chunk)
                kept = [batch.column(i).slice(chunk.row0, chunk.n) for i in range(n_keep)]
                yield pa.RecordBatch.from_arrays(
                    kept + [v if isinstance(v, pa.Array) else pa.array(v) for v in made.values()], names=keep + list(made)
                )

    return source.mapInArrow(run, f"{kinds}, {schema}" if keep else schema)


def ranked(df: DataFrame, group: list[str], order: str, name: str, *, spread: int = 65_536, least: int = 1024) -> DataFrame:
    """df with the rank (from 0) of each row within its group by a bigint column, nulls first; ties in any order.

    Rows are ranked within ranges of the order column, at most spread of them, and each range starts after
    the counts of those before it; so no group's rows meet in one task, however large it is. Rows without a value are
    dealt by a hash of their other numbers. Rows move once: the starts meet them as the ranking dealt them.
    """
    ends = df.agg(F.min(order).alias("lo"), F.max(order).alias("hi")).first()
    lo = ends.lo or 0
    width = max(least, ((ends.hi or 0) - lo) // spread + 1)
    numbers = [f"`{f.name}`" for f in df.schema if f.name not in (*group, order) and isinstance(f.dataType, NumericType)]
    none = -1 - F.pmod(F.xxhash64(*numbers), F.lit(spread)) if numbers else F.lit(-1).cast("bigint")
    cut = df.withColumns({"_group": F.struct(*group), "_range": F.coalesce(F.floor((F.col(order) - F.lit(lo)) / width).cast("bigint"), none)})
    within = cut.withColumn("_nth", F.row_number().over(Window.partitionBy("_group", "_range").orderBy(order)) - 1)
    counts = cut.groupBy("_group", "_range").agg(F.count("*").alias("_n"))
    before = Window.partitionBy("_group").orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(F.col("_group").alias("_g"), F.col("_range").alias("_r"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    joined = within.join(starts, (F.col("_group") == F.col("_g")) & (F.col("_range") == F.col("_r")))
    return joined.withColumn(name, (F.col("_start") + F.col("_nth")).cast("bigint")).drop("_group", "_range", "_nth", "_g", "_r", "_start")
