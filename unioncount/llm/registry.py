"""Queries of the corpus operators and the SQL of those that SQL can express."""

from __future__ import annotations

from . import ann, grace_dedup, langid, mixing, packing, simhash, substrings, token_counts, token_store, toxicity

QUERIES = {
    "op1_mix_sources": mixing.op1_mix_sources,
    "op2_token_store": token_store.op2_token_store,
    "op3_neighbours": ann.op3_neighbours,
    "op4_near_duplicates": simhash.op4_near_duplicates,
    "op5_language_id": langid.op5_language_id,
    "op6_pack": packing.op6_pack,
    "op7_toxic_spans": toxicity.op7_toxic_spans,
    "op8_token_counts": token_counts.op8_token_counts,
    "op9_repeated_passages": substrings.op9_repeated_passages,
    "op10_exact_dedup": grace_dedup.op10_exact_dedup,
}
ORACLES = {"op10_exact_dedup": grace_dedup.SQL}
