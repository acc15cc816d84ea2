"""The operators' queries and the SQL of those that SQL can express."""

from motifprune.llm import decontamination, exact_dedup, html_text, language_id, lm_scoring, near_dedup, packing, quality, sharding, token_output

QUERIES = {
    "op1_best_fit_packing": packing.op1_best_fit_packing,
    "op2_latent_decontamination": decontamination.op2_latent_decontamination,
    "op3_quality_rules": quality.op3_quality_rules,
    "op4_exact_dedup": exact_dedup.op4_exact_dedup,
    "op5_token_parquet": token_output.op5_token_parquet,
    "op6_url_differencing": html_text.op6_url_differencing,
    "op7_context_mixing": lm_scoring.op7_context_mixing,
    "op8_setsketch_near_dedup": near_dedup.op8_setsketch_near_dedup,
    "op9_label_propagation_shards": sharding.op9_label_propagation_shards,
    "op10_language_id": language_id.op10_language_id,
}
ORACLES = {"op4_exact_dedup": exact_dedup.ORACLE}
