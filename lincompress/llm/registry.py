"""The queries of this folder and their SQL."""

from __future__ import annotations

from lincompress.llm import language_id, license_scan, line_dedup, lm_scoring, nn_descent, packing, piece_sampling, quality_classifier, quality_rules, simhash

QUERIES = {
    "op1_quality_rules": quality_rules.op1_quality_rules,
    "op2_piece_sampling": piece_sampling.op2_piece_sampling,
    "op3_nn_descent": nn_descent.op3_nn_descent,
    "op4_license_scan": license_scan.op4_license_scan,
    "op5_line_dedup": line_dedup.op5_line_dedup,
    "op5_line_dedup_whole": line_dedup.op5_line_dedup_whole,
    "op6_packing": packing.op6_packing,
    "op7_language_id": language_id.op7_language_id,
    "op8_lm_scoring": lm_scoring.op8_lm_scoring,
    "op9_quality_classifier": quality_classifier.op9_quality_classifier,
    "op10_simhash_near_dedup": simhash.op10_simhash_near_dedup,
}
SQL = {
    "op1_quality_rules": quality_rules.SQL,
    "op5_line_dedup": line_dedup.SQL,
    "op5_line_dedup_whole": line_dedup.WHOLE_SQL,
}
