"""The corpus queries by name, and their DuckDB forms."""

from __future__ import annotations

from unischema.llm import chat_format, decontamination, exact_dedup, language_id, license_scan, line_dedup, near_dedup, packing, quality, sharding

QUERIES = {
    f.__name__: f
    for f in (
        exact_dedup.op1_exact_dedup,
        decontamination.op2_decontamination,
        chat_format.op3_chat_formatting,
        quality.op4_quality_classifier,
        near_dedup.op5_minhash_near_dedup,
        license_scan.op6_license_scan,
        language_id.op7_language_id,
        sharding.op8_rendezvous_sharding,
        line_dedup.op9_line_dedup,
        packing.op10_best_fit_packing,
    )
}

ORACLES = {"op1_exact_dedup": exact_dedup.ORACLE, "op2_decontamination": decontamination.ORACLE, "op5_minhash_near_dedup": near_dedup.ORACLE, "op3_chat_formatting": chat_format.ORACLE, "op9_line_dedup": line_dedup.ORACLE}
