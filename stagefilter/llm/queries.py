"""The operators as registered queries over their whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline

from stagefilter.llm import twins
from stagefilter.llm.ann import nearest
from stagefilter.llm.common import table
from stagefilter.llm.jaccard import jaccard_classes
from stagefilter.llm.langid import identify
from stagefilter.llm.linededup import GROWING, line_classes
from stagefilter.llm.mixing import mix_sources
from stagefilter.llm.packing import pack
from stagefilter.llm.pii import personal_data
from stagefilter.llm.quality import quality_rules
from stagefilter.llm.secrets import find_secrets
from stagefilter.llm.substring import substring_dedup


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "documents"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(table(spark, sf_dir, "documents"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"))


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(table(spark, sf_dir, "documents"))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(table(spark, sf_dir, "documents"))


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents"))


def op8_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return nearest(vectors, vectors.filter("vec_id % 50 = 0"))


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules(table(spark, sf_dir, "documents"))
    return judged.drop("rest", "n_rest_words", "n_rest_repeat_words", "rest_failed")


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_classes(table(spark, sf_dir, "documents"), GROWING).drop("version")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"op1_language_id": op1_language_id, "op2_packing": op2_packing, "op3_secrets": op3_secrets, "op4_mixing": op4_mixing, "op5_substring_dedup": op5_substring_dedup, "op6_pii": op6_pii, "op7_jaccard_join": op7_jaccard_join, "op8_ann": op8_ann, "op9_quality_rules": op9_quality_rules, "op10_line_dedup": op10_line_dedup, "pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op7_jaccard_join": twins.JACCARD, "op9_quality_rules": twins.QUALITY}
