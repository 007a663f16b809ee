"""Queries of this subpackage and the SQL that says the same."""

from __future__ import annotations

from parinflate.llm import byte_bpe, exact_dedup, html_extract, importance, licenses, minhash_dedup, mixing, quality_rules, token_counts, toxicity

QUERIES = {
    "op1_html_extract": html_extract.op1_html_extract,
    "op2_toxicity": toxicity.op2_toxicity,
    "op3_byte_bpe": byte_bpe.op3_byte_bpe,
    "op4_token_counts": token_counts.op4_token_counts,
    "op5_license_scan": licenses.op5_license_scan,
    "op6_quality_importance": importance.op6_quality_importance,
    "op7_quality_rules": quality_rules.op7_quality_rules,
    "op8_exact_dedup": exact_dedup.op8_exact_dedup,
    "op9_minhash_dedup": minhash_dedup.op9_minhash_dedup,
    "op10_mix_sources": mixing.op10_mix_sources,
}

ORACLES = {
    "op7_quality_rules": quality_rules.OP7_SQL,
    "op8_exact_dedup": exact_dedup.OP8_SQL,
}
