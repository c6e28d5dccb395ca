"""Queries of the operators, and their SQL where SQL can express them."""

from __future__ import annotations

from . import decontaminate, fingerprints, lines, near, packing, pii, quality, secrets, suffix_tree, toxicity

QUERIES = {
    "op1_toxicity": toxicity.op1_toxicity,
    "op2_best_fit_packing": packing.op2_best_fit_packing,
    "op3_secret_findings": secrets.op3_secret_findings,
    "op4_pii_spans": pii.op4_pii_spans,
    "op5_benchmark_leaks": decontaminate.op5_benchmark_leaks,
    "op6_quality_ranking": quality.op6_quality_ranking,
    "op7_suffix_tree": suffix_tree.op7_suffix_tree,
    "op8_three_line_windows": lines.op8_three_line_windows,
    "op9_min_max_near_duplicates": near.op9_min_max_near_duplicates,
    "op10_bottom_k_fingerprints": fingerprints.op10_bottom_k_fingerprints,
}
ORACLES = {"op8_three_line_windows": lines.OP8_SQL}
