"""The registered queries of this subpackage and, where SQL can say it, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pathalgebra.llm import html_text, langid, licenses, mixing, near_dup, packing, quality, token_store, toxicity, vectors
from pathalgebra.runtime import stored, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_page_differencing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.main_text(table(spark, sf_dir, "pages"))


def op2_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify_languages(table(spark, sf_dir, "documents"))


def op3_curriculum(spark: SparkSession, sf_dir: str) -> DataFrame:
    # Stored first: the range sort reads its input twice, once for the borders.
    mixed = stored(mixing.mix_sources(table(spark, sf_dir, "documents")), "mixed")
    return mixing.training_order(mixed, untaken=True)


def op4_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.encode_corpus(table(spark, sf_dir, "documents"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_adaptive_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.adaptive_quality(table(spark, sf_dir, "documents"))


def op7_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "documents"), width=3, percent=85)


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.license_scan(table(spark, sf_dir, "documents"))


def op9_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.near_vectors(table(spark, sf_dir, "embeddings"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Query]:
    found = (op1_page_differencing, op2_crf_language, op3_curriculum, op4_token_store, op5_toxicity, op6_adaptive_quality, op7_near_dup, op8_license_scan, op9_vectors, op10_packing)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op3_curriculum": mixing.SQL, "op6_adaptive_quality": quality.sql(), "op8_license_scan": licenses.sql()}
