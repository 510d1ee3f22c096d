"""Registry of this subpackage: queries and the SQL that says the same."""

from __future__ import annotations

from nearcopy.llm import decontam, media, ngram_join, packing, parsing, passages, pii, token_store, toxicity, url_filter

QUERIES = {
    "op1_url_filter": url_filter.op1_url_filter,
    "op2_pii_pseudonyms": pii.op2_pii_pseudonyms,
    "op3_decontamination": decontam.op3_decontamination,
    "op4_media_columns": media.op4_media_columns,
    "op5_ngram_jaccard_join": ngram_join.op5_ngram_jaccard_join,
    "op6_token_store": token_store.op6_token_store,
    "op7_toxicity": toxicity.op7_toxicity,
    "op8_repeated_passages": passages.op8_repeated_passages,
    "op9_packing": packing.op9_packing,
    "op10_repeat_removal": parsing.op10_repeat_removal,
}

ORACLES = {
    "op1_url_filter": url_filter.ORACLE_OP1,
    "op3_decontamination": decontam.ORACLE_OP3,
}
