"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from synthguard.llm import fingerprint, jaccard_join, language, language_model, line_dedup, metric_search, packing, quality, sentence_pieces, suffix_dedup

QUERIES = {
    "op1_line_dedup": line_dedup.query,
    "op2_sentence_pieces": sentence_pieces.query,
    "op3_quality": quality.query,
    "op4_language": language.query,
    "op5_ngram_jaccard": jaccard_join.query,
    "op6_suffix_dedup": suffix_dedup.query,
    "op7_fingerprints": fingerprint.query,
    "op8_exact_top_k": metric_search.query,
    "op9_packing": packing.query,
    "op10_lm_scoring": language_model.query,
    "fingerprint_edits": fingerprint.edits,
    "fingerprint_matches": fingerprint.alike,
    "lm_base_scores": language_model.base,
}
SQL = {
    "op1_line_dedup": line_dedup.SQL,
    "op5_ngram_jaccard": jaccard_join.SQL,
    "op6_suffix_dedup": suffix_dedup.SQL,
    "op8_exact_top_k": metric_search.SQL,
    "fingerprint_edits": fingerprint.EDITS_SQL,
    "lm_base_scores": language_model.BASE_SQL,
}
