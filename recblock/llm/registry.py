"""Queries of this folder and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from recblock.llm import collision_ann, language_id, license_scan, minhash_join, packing, pii, quality_rules, source_mix, suffix_dedup, url_filter


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_suffix_dedup": suffix_dedup.op1_suffix_dedup,
        "op2_url_filter": url_filter.op2_url_filter,
        "op3_language_id": language_id.op3_language_id,
        "op4_minhash_near_dedup": minhash_join.op4_minhash_near_dedup,
        "op5_quality_rules": quality_rules.op5_quality_rules,
        "op6_collision_ann": collision_ann.op6_collision_ann,
        "op7_source_mix": source_mix.op7_source_mix,
        "op8_license_scan": license_scan.op8_license_scan,
        "op9_pii": pii.op9_pii,
        "op10_best_fit_packing": packing.op10_best_fit_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_url_filter": url_filter.OP2_SQL, "op5_quality_rules": quality_rules.OP5_SQL, "op7_source_mix": source_mix.OP7_SQL}
