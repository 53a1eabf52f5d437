"""Queries and SQL of this subpackage, as ``__spark_entry__`` registers them."""

from __future__ import annotations

from . import decontamination, language_model, near_dedup, oracles, packing, quality_rules, secrets, substring_dedup, suffix_dedup, token_counts, toxicity


def queries() -> dict:
    return {
        "op1_secret_scan": secrets.op1_secret_scan,
        "op2_benchmark_decontamination": decontamination.op2_benchmark_decontamination,
        "op3_quality_rules": quality_rules.op3_quality_rules,
        "op4_language_model": language_model.op4_language_model,
        "op5_substring_dedup": substring_dedup.op5_substring_dedup,
        "op6_minhash_near_dedup": near_dedup.op6_minhash_near_dedup,
        "op7_suffix_array_dedup": suffix_dedup.op7_suffix_array_dedup,
        "op8_token_counts": token_counts.op8_token_counts,
        "op9_toxicity": toxicity.op9_toxicity,
        "op10_best_fit_packing": packing.op10_best_fit_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_benchmark_decontamination": decontamination.OP2_SQL, "op5_substring_dedup": oracles.OP5_SQL, "op6_minhash_near_dedup": near_dedup.OP6_SQL, "op7_suffix_array_dedup": oracles.OP7_SQL}
