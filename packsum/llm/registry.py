"""Queries and SQL of the training-data operators, for the driver's entry module."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from packsum.llm import chroma, language, maxent, mixing, packing, privacy, quality, repeats, setjoin, toxicity


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxent.language_model(table(spark, sf_dir, "documents"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(table(spark, sf_dir, "documents"))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_rules(table(spark, sf_dir, "documents"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return setjoin.jaccard_components(table(spark, sf_dir, "documents"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_toxicity": toxicity.query,
        "op2_maxent_lm": op2,
        "op3_disclosure_pii": privacy.query,
        "op4_chroma_fingerprints": chroma.query,
        "op5_language_id": language.query,
        "op6_repeated_passages": op6,
        "op7_best_fit_packing": op7,
        "op8_quality_rules": op8,
        "op9_jaccard_join": op9,
        "op10_source_mixing": op10,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {"op6_repeated_passages": repeats.oracle(), "op8_quality_rules": quality.oracle(), "op9_jaccard_join": setjoin.oracle(), "op10_source_mixing": mixing.oracle()}
