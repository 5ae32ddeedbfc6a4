"""Queries of the training-data operators and, where SQL can express one, its SQL."""

from __future__ import annotations

from relmix.llm import bpe, exact_dedup, flac, html_main, licenses, mixing, near_dedup, quality, token_counts, toxicity


def queries() -> dict:
    return {
        "op1_quality": quality.op1_quality,
        "op2_exact_dedup": exact_dedup.op2_exact_dedup,
        "op3_byte_bpe": bpe.op3_byte_bpe,
        "op4_flac": flac.op4_flac,
        "op5_token_counts": token_counts.op5_token_counts,
        "op6_main_text": html_main.op6_main_text,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_near_dedup": near_dedup.op8_near_dedup,
        "op9_license_scan": licenses.op9_license_scan,
        "op10_mix_sources": mixing.op10_mix_sources,
    }


def oracle_sql() -> dict:
    return {"op2_exact_dedup": exact_dedup.OP2_SQL, "op9_license_scan": licenses.OP9_SQL, "op10_mix_sources": mixing.OP10_SQL}
