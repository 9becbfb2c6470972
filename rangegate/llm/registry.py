"""Queries and DuckDB texts of the training-data operators."""

from rangegate.llm import exact_dedup, line_dedup, line_rules, lm_score, mixing, near_dedup, packing, quality, substring_dedup, token_shards

QUERIES = {
    "op1_line_rules": line_rules.op1_line_rules,
    "op2_harmonic_packing": packing.op2_harmonic_packing,
    "op3_ordinal_quality": quality.op3_ordinal_quality,
    "op4_context_mixing": lm_score.op4_context_mixing,
    "op5_near_duplicates": near_dedup.op5_near_duplicates,
    "op6_training_order": token_shards.op6_training_order,
    "op7_raked_mixing": mixing.op7_raked_mixing,
    "op8_cuckoo_exact_dedup": exact_dedup.op8_cuckoo_exact_dedup,
    "op9_repeated_passages": substring_dedup.op9_repeated_passages,
    "op10_line_dedup": line_dedup.op10_line_dedup,
}
ORACLES = {"op10_line_dedup": line_dedup.OP10_SQL, "op1_line_rules": line_rules.OP1_SQL, "op8_cuckoo_exact_dedup": exact_dedup.OP8_SQL, "op9_repeated_passages": substring_dedup.OP9_SQL}
