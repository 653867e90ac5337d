"""Queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from winsub.llm import op01_exact_dedup, op02_sentencepiece, op03_language_id, op04_packing, op05_transport_stream, op06_parity_join, op07_quality, op08_token_counts, op09_context_tree, op10_warc

QUERIES = {
    "op1_exact_dedup": op01_exact_dedup.query,
    "op2_sentencepiece": op02_sentencepiece.query,
    "op3_language_id": op03_language_id.query,
    "op4_packing": op04_packing.query,
    "op5_transport_stream": op05_transport_stream.query,
    "op6_parity_join": op06_parity_join.query,
    "op6_all_links": op06_parity_join.all_links_query,
    "op7_quality_attention": op07_quality.query,
    "op8_token_counts": op08_token_counts.query,
    "op9_context_tree": op09_context_tree.query,
    "op10_warc_bundles": op10_warc.query,
}
ORACLES = {
    "op1_exact_dedup": op01_exact_dedup.ORACLE,
    "op10_warc_bundles": op10_warc.ORACLE,
}
