"""Queries of the document operators."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from concord.llm import bpe, cotraining, decontamination, gif, license_scan, pii, secret_scan, sharding, simhash, toxicity

VOCABULARY = public_tokenizers.path("byte_bpe_50k.tiktoken")


def _pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "pipeline": _pipeline,
        "op1_gif": lambda spark, d: gif.media_digest(_docs(spark, d)),
        "op2_simhash": lambda spark, d: simhash.near_duplicates(_docs(spark, d)),
        "op3_sharding": lambda spark, d: sharding.shard(_docs(spark, d)),
        "op4_secrets": lambda spark, d: secret_scan.secrets(_docs(spark, d), by_window=True),
        "op5_licenses": lambda spark, d: license_scan.license_report(_docs(spark, d)),
        "op6_bpe": lambda spark, d: bpe.token_digest(_docs(spark, d), VOCABULARY, public_tokenizers.PATTERN),
        "op7_pii": lambda spark, d: pii.personal_data(_docs(spark, d)),
        "op8_quality": lambda spark, d: cotraining.quality(_docs(spark, d), spark.read.parquet(f"{d}/labels.parquet")),
        "op9_decontamination": lambda spark, d: decontamination.contamination(_docs(spark, d), spark.read.parquet(f"{d}/benchmark.parquet")),
        "op10_toxicity": lambda spark, d: toxicity.toxicity(_docs(spark, d), spark.read.parquet(f"{d}/labels.parquet")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op5_licenses": license_scan.oracle(), "op9_decontamination": decontamination.ORACLE}
