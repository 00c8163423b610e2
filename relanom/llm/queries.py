"""Queries of the training-data operators and, where SQL can express them, their oracles."""

from relanom.llm import decontaminate, language_id, near_dups, packing, pii, substring_dedup, suffix_dedup, url_rules, vector_links, warc

QUERIES = {
    "op1_warc_derivatives": warc.op1_warc_derivatives,
    "op2_winnowing": decontaminate.op2_winnowing,
    "op3_suffix_array_dedup": suffix_dedup.op3_suffix_array_dedup,
    "op4_surrogates": pii.op4_surrogates,
    "op5_url_rules": url_rules.op5_url_rules,
    "op6_cross_parsing": language_id.op6_cross_parsing,
    "op7_super_kmer_dedup": substring_dedup.op7_super_kmer_dedup,
    "op8_min_bin_slack": packing.op8_min_bin_slack,
    "op9_prob_minhash": near_dups.op9_prob_minhash,
    "op10_collision_counting": vector_links.op10_collision_counting,
}
ORACLES = {
    "op2_winnowing": decontaminate.ORACLE,
    "op5_url_rules": url_rules.ORACLE,
}
