"""Distance expressions that stay inside generated code: words are plain BIGINT columns, never arrays."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from twoview.operators.model import ModelSpec


def l2sq(a: Column, b: Column) -> Column:
    """Squared Euclidean distance of two arrays, summed from the left in double precision."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)


def dot(a: Column, b: Column) -> Column:
    """Inner product of two arrays, summed from the left."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def word_columns(prefix: str, n: int) -> list[Column]:
    return [F.col(f"{prefix}{i}") for i in range(n)]


def hamming(a: list[Column], b: list[Column]) -> Column:
    """Differing bits of two codes given as words."""
    return reduce(lambda x, y: x + y, [F.bit_count(x.bitwiseXOR(y)) for x, y in zip(a, b, strict=True)])


def code_at(words: list[Column], m: int, spec: ModelSpec) -> Column:
    """Number of sub-quantizer m, out of the words."""
    return F.shiftrightunsigned(words[m // spec.per_word], spec.b * (m % spec.per_word)).bitwiseAND(F.lit(spec.K - 1).cast("bigint")).cast("int")


def adc(words: list[Column], lut: Column, spec: ModelSpec) -> Column:
    """Squared distance from a raw query to a code, by M look-ups in its flat table; unrolled, as lambdas are interpreted."""
    return reduce(lambda x, y: x + y, [F.get(lut, F.lit(m * spec.K) + code_at(words, m, spec)) for m in range(spec.M)])


def mismatch(a: list[Column], b: list[Column], spec: ModelSpec) -> Column:
    """In how many sub-quantizers two codes differ: the bits of each number fold onto its lowest one."""
    low = sum(1 << (spec.b * i) for i in range(spec.per_word))
    low = low - (1 << 64) if low >= 1 << 63 else low

    def one(x: Column, y: Column) -> Column:
        d = x.bitwiseXOR(y)
        folded = reduce(lambda p, q: p.bitwiseOR(q), [F.shiftrightunsigned(d, s) if s else d for s in range(spec.b)])
        return F.bit_count(folded.bitwiseAND(F.lit(low).cast("bigint")))

    return reduce(lambda x, y: x + y, [one(x, y) for x, y in zip(a, b, strict=True)])


def pack(codes: Column, spec: ModelSpec) -> list[Column]:
    """Words of a column of M numbers."""
    out = []
    for w in range(spec.n_words):
        part = range(w * spec.per_word, min(spec.M, (w + 1) * spec.per_word))
        out.append(reduce(lambda x, y: x.bitwiseOR(y), [F.shiftleft(F.get(codes, m).cast("bigint"), spec.b * (m % spec.per_word)) for m in part]).alias(f"w{w}"))
    return out


def unpack(words: list[Column], spec: ModelSpec) -> Column:
    """The M numbers of a code's words."""
    return F.array(*[code_at(words, m, spec) for m in range(spec.M)])


def register_sql_functions(spark: SparkSession) -> None:
    """hamming64, hamming128 and l2sq for SQL; their bodies are inlined into plans."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hamming64(a BIGINT, b BIGINT) RETURNS INT RETURN bit_count(a ^ b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hamming128(a0 BIGINT, a1 BIGINT, b0 BIGINT, b1 BIGINT) RETURNS INT RETURN bit_count(a0 ^ b0) + bit_count(a1 ^ b1)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION l2sq(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE "
        "RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, v) -> s + v)"
    )
