"""Query and oracle registry of the training-data operators."""

from __future__ import annotations

from rulecredit.llm import (
    chunk_bpe,
    jaccard_join,
    oracles,
    packing,
    quality,
    substring,
    suffix_dedup,
    token_counts,
    toxicity,
    url_filter,
    vector_dedup,
)

QUERIES = {
    "op1_bpe_chunk_reuse": chunk_bpe.op1_bpe_chunk_reuse,
    "op2_quality_rules": quality.op2_quality_rules,
    "op3_best_fit_packing": packing.op3_best_fit_packing,
    "op4_suffix_automata_dedup": substring.op4_suffix_automata_dedup,
    "op5_token_rollup": token_counts.op5_token_rollup,
    "op6_url_language_model": url_filter.op6_url_language_model,
    "op7_pstable_vectors": vector_dedup.op7_pstable_vectors,
    "op8_toxicity_lexicon": toxicity.op8_toxicity_lexicon,
    "op9_suffix_interval_dedup": suffix_dedup.op9_suffix_interval_dedup,
    "op10_size_aware_jaccard": jaccard_join.op10_size_aware_jaccard,
}

#: The others hold BPE ids or learned models, or are too slow in SQL on whole tables
#: (400-byte windows); tests hold them against brute force.
ORACLES = {
    "op2_quality_rules": quality.SQL,
    "op4_suffix_automata_dedup": oracles.SUBSTRING,
    "op7_pstable_vectors": oracles.VECTORS,
    "op10_size_aware_jaccard": oracles.JACCARD,
}
