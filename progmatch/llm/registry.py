"""The queries of this subpackage and, where SQL can express them, their SQL twins."""

from __future__ import annotations

from progmatch.llm import fingerprints, jaccard_join, language_id, mixing, piece_codec, quality_nbsvm, quality_rules, secrets, suffix_dedup, token_files

QUERIES = {
    "op1_piece_codec": piece_codec.op1_piece_codec,
    "op2_document_fingerprints": fingerprints.op2_document_fingerprints,
    "op3_suffix_dedup": suffix_dedup.op3_suffix_dedup,
    "op4_mix_sources": mixing.op4_mix_sources,
    "op5_secret_scans": secrets.op5_secret_scans,
    "op6_token_binary": token_files.op6_token_binary,
    "op7_quality_classifier": quality_nbsvm.op7_quality_classifier,
    "op8_language_id": language_id.op8_language_id,
    "op9_ngram_jaccard_join": jaccard_join.op9_ngram_jaccard_join,
    "op10_quality_rules": quality_rules.op10_quality_rules,
}
ORACLES = {"op4_mix_sources": mixing.OP4_SQL, "op10_quality_rules": quality_rules.OP10_SQL}
