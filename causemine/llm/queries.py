"""The registered queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from . import (
    decontamination,
    html_extraction,
    language_id,
    near_dedup,
    packing,
    quality_rules,
    sharding,
    token_counts,
    token_files,
    toxicity,
)

QUERIES = {
    "op1_near_dedup": near_dedup.query,
    "op2_packing": packing.query,
    "op3_toxicity": toxicity.query,
    "op4_token_counts": token_counts.query,
    "op5_language_id": language_id.query,
    "op6_quality_rules": quality_rules.query,
    "op7_decontamination": decontamination.query,
    "op8_html_extraction": html_extraction.query,
    "op9_token_files": token_files.query,
    "op10_sharding": sharding.query,
}

ORACLES: dict[str, str] = {
    "op1_near_dedup": near_dedup.SQL,
    "op7_decontamination": decontamination.SQL,
}
