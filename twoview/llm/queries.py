"""The registered queries of this subpackage, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.llm.base import table


def _remainder(n: int) -> F.Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.toxicity import toxicity

    known = table(spark, sf_dir, "labels").where(_remainder(4) != 2)
    out = toxicity(table(spark, sf_dir, "documents"), known)
    return out.select("doc_id", F.coalesce(_remainder(4) == 2, F.lit(False)).alias("held_out"), "score", "predicted")


def op2_projected_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.projected_search import projected_search

    return projected_search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.quality_rules import quality_rules

    out = quality_rules(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "score")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.mixing import mix_sources

    return mix_sources(table(spark, sf_dir, "documents").select("doc_id", "source"))


def op6_quality_grades(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grades: 0 for labelled low quality, 1 for good but toxic, 2 for good and clean."""
    from twoview.llm.grading import quality_grades

    labels = table(spark, sf_dir, "labels")
    ratings = labels.select("doc_id", F.when(F.col("quality") <= 0, 0).when(F.col("toxic") > 0, 1).otherwise(2).alias("grade"))
    return quality_grades(table(spark, sf_dir, "documents"), ratings)


def op7_attention_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.attention_lm import language_model_scores
    from twoview.llm.token_store import default_path

    docs = table(spark, sf_dir, "documents")
    held = F.coalesce(_remainder(7) == 2, F.lit(False))
    out = language_model_scores(docs, ~held, default_path("word_bpe_49k.json"))
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op8_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.token_store import default_path, store_digest

    return store_digest(spark, table(spark, sf_dir, "documents"), default_path("word_bpe_49k.json"), 2)


def op9_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.ngram_join import ngram_components

    return ngram_components(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def op10_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from twoview.llm.private_data import private_data

    out = private_data(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_id")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_toxicity": op1_toxicity,
    "op2_projected_search": op2_projected_search,
    "op3_packing": op3_packing,
    "op4_quality_rules": op4_quality_rules,
    "op5_mixing": op5_mixing,
    "op6_quality_grades": op6_quality_grades,
    "op7_attention_lm": op7_attention_lm,
    "op8_token_store": op8_token_store,
    "op9_ngram_join": op9_ngram_join,
    "op10_private_data": op10_private_data,
    "pipeline": pipeline,
}


def _sql() -> dict[str, str]:
    from twoview.llm.mixing import oracle

    return {"op5_mixing": oracle()}


SQL: dict[str, str] = _sql()
