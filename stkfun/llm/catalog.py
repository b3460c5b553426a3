"""Queries of this subpackage and their SQL."""

from __future__ import annotations

from stkfun.llm import divergence_rules, ftrl_quality, hpy_lm, license_scan, phrase_dedup, pii_sanitize, simhash_pivots, slot_sharding, source_mix, tiling_decontam


def queries() -> dict:
    return {
        "op1_simhash_pivots": simhash_pivots.op1_query,
        "op2_license_scan": license_scan.op2_query,
        "op3_slot_sharding": slot_sharding.op3_query,
        "op4_phrase_dedup": phrase_dedup.op4_query,
        "op5_source_mix": source_mix.op5_query,
        "op6_pii_sanitize": pii_sanitize.op6_query,
        "op7_hpy_lm": hpy_lm.op7_query,
        "op8_divergence_rules": divergence_rules.op8_query,
        "op9_ftrl_quality": ftrl_quality.op9_query,
        "op10_tiling_decontam": tiling_decontam.op10_query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_slot_sharding": slot_sharding.OP3_SQL, "op5_source_mix": source_mix.OP5_SQL, "op8_divergence_rules": divergence_rules.OP8_SQL}
