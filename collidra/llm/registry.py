"""Queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from . import bpe, exact_dedup, html_text, mixing, paragraph_sketch, quality, sharding, simhash, substring_dedup, toxicity

QUERIES = {
    "op1_paragraph_sketch": paragraph_sketch.op1_paragraph_sketch,
    "op2_toxicity": toxicity.op2_toxicity,
    "op3_substring_dedup": substring_dedup.op3_substring_dedup,
    "op4_html_text": html_text.op4_html_text,
    "op5_mixing": mixing.op5_mixing,
    "op6_sharding": sharding.op6_sharding,
    "op7_simhash": simhash.op7_simhash,
    "op8_quality": quality.op8_quality,
    "op9_exact_dedup": exact_dedup.op9_exact_dedup,
    "op10_bpe": bpe.op10_bpe,
}
ORACLES = {"op9_exact_dedup": exact_dedup.ORACLE_SQL}
