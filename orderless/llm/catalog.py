"""Queries of the text operators and the SQL that restates them, where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import byte_bpe, exact_dedup, fingerprints, license_texts, near_dedup, packing, pii, quality, secrets, substring_dedup


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_best_fit_packing": packing.query,
        "op2_fingerprints": fingerprints.query,
        "op3_suffix_array": substring_dedup.query,
        "op4_license_texts": license_texts.query,
        "op5_pii": pii.query,
        "op6_exact_dedup": exact_dedup.query,
        "op7_secrets": secrets.query,
        "op8_quality": quality.query,
        "op9_byte_bpe": byte_bpe.query,
        "op10_ngram_jaccard": near_dedup.query,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_license_texts": license_texts.sql(), "op6_exact_dedup": exact_dedup.SQL}
