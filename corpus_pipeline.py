"""A corpus from raw documents to packed sequences, stage by stage.

Every stage takes (spark, docs, sf_dir) and returns a frame; it is written as
Parquet and read again before the next stage starts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathalgebra.llm import langid, mixing, near_dup, packing, toxicity
from pathalgebra.runtime import kept, scratch, table

#: A document goes if its text has no letter, or if no language has this share of its words.
LEAST_SHARE = 0.4


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labelled = langid.language_labels(docs, langid.fit_languages(docs), keep=tuple(docs.columns))
    return labelled.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SHARE)).select(*docs.columns)


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    net = toxicity.fit_toxicity(docs, table(spark, sf_dir, "labels"))
    return toxicity.toxicity_scores(docs, net, keep=tuple(docs.columns)).where("score < 0.5").select(*docs.columns)


def near_dup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.without_near_duplicates(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_by_mix(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("language", language_stage),
    ("toxicity", toxicity_stage),
    ("near_dup", near_dup_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]

#: Learned classifiers decide, which SQL cannot express; tests/llm/test_pipeline.py reruns every stage by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        with scratch(spark):
            docs = kept(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
