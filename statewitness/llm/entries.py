"""Registered queries of the training-data operators, and their oracle SQL where SQL can express them."""

from __future__ import annotations

from statewitness.llm import decontaminate, exact_dedup, line_dedup, near_dedup, packing, quality, sharding, substring_dedup, url_trust, web_archive


def queries() -> dict:
    return {
        "op1_quality_rules": quality.query,
        "op2_substring_dedup": substring_dedup.query,
        "op3_exact_dedup": exact_dedup.query,
        "op4_best_fit_packing": packing.query,
        "op5_minhash_near_dedup": near_dedup.query,
        "op6_fuzzy_lines": line_dedup.query,
        "op7_url_trust": url_trust.query,
        "op8_shard_lookup": sharding.query,
        "op9_decontamination": decontaminate.query,
        "op10_arc_to_warc": web_archive.query,
    }


def oracle_sql() -> dict:
    return {
        "op2_substring_dedup": substring_dedup.ORACLE,
        "op10_arc_to_warc": web_archive.ORACLE,
        "op3_exact_dedup": exact_dedup.ORACLE,
        "op7_url_trust": url_trust.ORACLE,
        "op8_shard_lookup": sharding.oracle(),
    }
