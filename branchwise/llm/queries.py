"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import fingerprints, hmm_lm, mixing, near_duplicates, packing, pii, quality_classifier, quality_rules, secrets, token_files

QUERIES = {
    "op1_ngram_jaccard_join": near_duplicates.op1,
    "op2_quality_rules": quality_rules.op2,
    "op3_source_mixing": mixing.op3,
    "op4_best_fit_packing": packing.op4,
    "op5_token_files": token_files.op5,
    "op6_secret_scans": secrets.op6,
    "op7_quality_classifier": quality_classifier.op7,
    "op8_document_fingerprints": fingerprints.op8,
    "op9_pii": pii.op9,
    "op10_hmm_lm": hmm_lm.op10,
}

ORACLE_SQL: dict[str, str] = {}
