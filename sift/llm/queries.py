"""The registered queries of this subpackage and their SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sift.llm import bases, chunks, decontam, licenses, lm, neardup, packing, quality, reputation, secrets, tokencounts

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_rules": quality.op1_quality_rules,
    "op2_url_filters": reputation.op2_url_filters,
    "op3_best_fit_packing": packing.op3_best_fit_packing,
    "op4_license_scans": licenses.op4_license_scans,
    "op5_benchmark_decontamination": decontam.op5_benchmark_decontamination,
    "op6_secret_scans": secrets.op6_secret_scans,
    "op7_substring_dedup": chunks.op7_substring_dedup,
    "op8_token_counts": tokencounts.op8_token_counts,
    "op9_lm_scoring": lm.op9_lm_scoring,
    "op10_simhash_near_dedup": neardup.op10_simhash_near_dedup,
    "quality_base": bases.quality_base,
    "secrets_base": bases.secrets_base,
    "lm_base": bases.lm_base,
}

ORACLES: dict[str, str] = {
    "op2_url_filters": reputation.ORACLE,
    "op5_benchmark_decontamination": decontam.ORACLE,
    "quality_base": bases.QUALITY,
    "secrets_base": bases.SECRETS,
    "lm_base": bases.LM,
}
