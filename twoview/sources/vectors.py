"""Vector sources over the given tables; every one gives (vec_id, embedding)."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twoview.operators.vectors import lists, standardize

LETTERS = "abcdefghijklmnopqrstuvwx"
LINES = ["l_quantity", "l_tax", "l_extendedprice", "l_discount", "ship_year", "ship_day", "l_partkey", "l_suppkey"]


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; columns are pruned and filters pushed by Catalyst."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stored unit vectors of 64 dimensions."""
    return read_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))


def letter_vector(text: F.Column) -> F.Column:
    """Counts of the letters a to x over the text's length."""
    low = F.lower(text)
    n = F.greatest(F.length(text), F.lit(1))
    return F.array(*[(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / n for c in LETTERS])


def letters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Letter frequencies of documents, 24 dimensions."""
    return read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), letter_vector(F.col("text")).alias("embedding"))


def convs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Letter frequencies of whole conversations, turns in order."""
    turns = read_table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "text"))).alias("t"))
    return turns.select(F.col("conv_id").alias("vec_id"), letter_vector(F.array_join(F.col("t.text"), " ")).alias("embedding"))


def web(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Letter frequencies of pages without their tags."""
    return read_table(spark, sf_dir, "pages").select(F.col("page_id").alias("vec_id"), letter_vector(F.regexp_replace("html", "<[^>]*>", "")).alias("embedding"))


def words(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    """Signed hashed bags of words of documents, at unit length; hashes that other engines have too.

    Words are counted where their text is, each distinct one hashed once a piece; what is dealt out is a row of sums a text.
    Texts of one id are one bag.
    """
    texts = read_table(spark, sf_dir, "documents").where("text IS NOT NULL").select(F.col("doc_id").alias("vec_id"), F.lower("text").cast("binary").alias("t"))
    kind = texts.schema["vec_id"].dataType.simpleString()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ends = np.cumsum(pc.binary_length(batch.column(1)).to_numpy().astype(np.int64))
            a = 0
            while a < batch.num_rows:  # texts of some megabytes together, one at least
                b = max(a + 1, int(np.searchsorted(ends, PIECE + (ends[a - 1] if a else 0), "right")))
                ids, sums = added(batch.column(0).slice(a, b - a), word_sums(batch.column(1).slice(a, b - a), dims))
                yield pa.RecordBatch.from_arrays([ids, pa.FixedSizeBinaryArray.from_buffers(pa.binary(8 * dims), len(ids), [None, pa.py_buffer(sums.tobytes())]).cast(pa.binary())], names=["vec_id", "sums"])
                a = b

    def unit(ids: pa.Array, sums: np.ndarray) -> pa.RecordBatch:
        x = sums.astype(float)
        return pa.RecordBatch.from_arrays([ids, lists(x / np.maximum(np.sqrt((x * x).sum(1)), 1e-300)[:, None])], names=["vec_id", "embedding"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last id so far, whose rows may go on in the next batch
        for batch in batches:
            if batch.num_rows:
                ids, sums = added(batch.column(0), np.frombuffer(b"".join(batch.column(1).to_pylist()), np.int64).reshape(-1, dims))
                if held and held[0][0].as_py() == ids[0].as_py():
                    sums[0] += held[1][0]
                elif held:
                    yield unit(*held)
                yield unit(ids[:-1], sums[:-1])
                held = ids[-1:], sums[-1:]
        if held:
            yield unit(*held)

    sums = texts.mapInArrow(count, f"vec_id {kind}, sums binary").repartition("vec_id").sortWithinPartitions("vec_id")
    return sums.mapInArrow(merge, f"vec_id {kind}, embedding array<double>")


def added(ids: pa.Array, rows: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """The sum of the rows of each id, ids in the order in which they come; null is an id."""
    coded = ids.dictionary_encode(null_encoding="encode")
    at = coded.indices.to_numpy()
    order = np.argsort(at, kind="stable")
    return coded.dictionary, np.add.reduceat(rows[order], np.searchsorted(at[order], np.arange(len(coded.dictionary))), axis=0)


#: Bytes of texts whose words are counted at a time.
PIECE = 4 << 20


def word_sums(texts: pa.Array, dims: int) -> np.ndarray:
    """Texts by dimensions: the sum of the signs of the words that hash there. Words lie between single spaces, and may be empty."""
    listed = pc.split_pattern(texts, b" ")
    found = listed.flatten().dictionary_encode()
    hashes = [hashlib.md5(w).digest() for w in found.dictionary.to_pylist()]  # noqa: S324
    at = np.array([int.from_bytes(h[:2], "big") % dims for h in hashes], np.int64)
    sign = np.array([-1.0 if h[2] >= 0x80 else 1.0 for h in hashes])
    i = found.indices.to_numpy()
    rows = np.repeat(np.arange(len(texts)), pc.list_value_length(listed).to_numpy())
    return np.bincount(rows * dims + at[i], sign[i], len(texts) * dims).astype(np.int64).reshape(len(texts), dims)


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Z-scores of order lines, 8 dimensions; line_id is a hash of the row, so that no global sort is needed."""
    t = read_table(spark, sf_dir, "lineitem")
    cols = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_tax", "l_discount", "l_shipdate"]
    raw = t.select(F.xxhash64(*cols).alias("vec_id"), *[F.col(c).cast("double").alias(c) for c in LINES if c in t.columns], F.year("l_shipdate").cast("double").alias("ship_year"), F.dayofyear("l_shipdate").cast("double").alias("ship_day"))
    return standardize(raw, LINES).select("vec_id", "embedding")


def plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Price and ship day of order lines in the unit square."""
    t = read_table(spark, sf_dir, "lineitem").select(
        F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice").alias("vec_id"), F.col("l_extendedprice").alias("x"), F.datediff("l_shipdate", F.lit("1995-01-01")).cast("double").alias("y")
    )
    ends = t.agg(*[f(c).alias(f"{n}_{c}") for c in "xy" for n, f in (("lo", F.min), ("hi", F.max))])
    unit = [(F.col(c) - F.col(f"lo_{c}")) / F.greatest(F.col(f"hi_{c}") - F.col(f"lo_{c}"), F.lit(1e-12)) for c in "xy"]
    return t.crossJoin(F.broadcast(ends)).select("vec_id", F.array(*unit).alias("embedding"))


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user: shares of all event types, mean and deviation of the value, share of week days."""
    e = read_table(spark, sf_dir, "events")
    return user_vectors(e.groupBy("user_id"), event_types(e))


def event_types(e: DataFrame, most: int = 1000) -> list[str]:
    """All event types in order; over most of them are no set of dimensions."""
    types = [r.event_type for r in e.select("event_type").distinct().orderBy("event_type").limit(most + 1).collect()]
    if len(types) > most:
        raise ValueError(f"more than {most} event types")
    return types


def user_vectors(grouped, types: list[str]) -> DataFrame:
    """The aggregate of users, also for windows of a stream."""
    n = F.count("*")
    shares = [F.count_if(F.col("event_type") == t) / n for t in types]
    v = F.array(*shares, F.avg("value") / 100, F.coalesce(F.stddev_pop("value"), F.lit(0.0)) / 100, F.count_if(F.dayofweek("ts").between(2, 6)) / n)
    return grouped.agg(v.alias("embedding")).withColumnRenamed("user_id", "vec_id")


def synthetic(spark: SparkSession, n: int, dims: int, clusters: int = 0, seed: int = 0) -> DataFrame:
    """n Gaussian vectors made from hashes of their ids, around as many centers; the same at any partitioning."""

    def normal(a: F.Column) -> F.Column:
        u1 = (F.shiftrightunsigned(F.xxhash64(a, F.lit(seed), F.lit(1)), 11) + 1) / F.lit(float(1 << 53))
        u2 = F.shiftrightunsigned(F.xxhash64(a, F.lit(seed), F.lit(2)), 11) / F.lit(float(1 << 53))
        return F.sqrt(-2 * F.log(u1)) * F.cos(2 * 3.141592653589793 * u2)

    ids = spark.range(n).withColumnRenamed("id", "vec_id")
    noise = [normal(F.col("vec_id") * dims + d) for d in range(dims)]
    if clusters:
        c = F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(clusters))
        noise = [v + 4 * normal(-(c * dims + d) - 1) for d, v in enumerate(noise)]
    return ids.select("vec_id", F.array(*noise).alias("embedding"))


def line_ids(t: DataFrame) -> DataFrame:
    """Dense ids of order lines by a window over one ordering; for tests at small sizes, as it sorts globally."""
    w = Window.orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    return t.withColumn("line_id", F.row_number().over(w))
