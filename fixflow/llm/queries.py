"""The queries of this package and the SQL that gives the same rows, where SQL can."""

from __future__ import annotations

from . import bpe, decontam, graph_ann, jaccard, langid, mixing, parse_dedup, sharding, substring, token_store

QUERIES = {
    "op1_bpe_roundtrip": bpe.op1,
    "op2_context_mixing": mixing.op2,
    "op3_graph_ann": graph_ann.op3,
    "op4_template_decontam": decontam.op4,
    "op5_substring_dedup": substring.op5,
    "op6_ring_sharding": sharding.op6,
    "op7_ngram_jaccard": jaccard.op7,
    "op8_parse_dedup": parse_dedup.op8,
    "op9_language_id": langid.op9,
    "op10_token_store": token_store.op10,
}

ORACLE: dict[str, str] = {}
