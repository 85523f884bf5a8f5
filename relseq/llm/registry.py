"""Queries of the corpus operators and, where SQL can express them, their DuckDB oracles."""

from __future__ import annotations

from relseq.llm import ann, language_id, line_dedup, media, mixing, near_dup, packing, quality, suffix_dedup, warc

QUERIES = {
    "op1_suffix_dedup": suffix_dedup.op1_suffix_dedup,
    "op2_media_lossless_webp": media.op2_media_lossless_webp,
    "op3_warc_transactions": warc.op3_warc_transactions,
    "op4_line_run_dedup": line_dedup.op4_line_run_dedup,
    "op5_language_id": language_id.op5_language_id,
    "op6_minhash_near_dedup": near_dup.op6_minhash_near_dedup,
    "op7_hnsw_neighbours": ann.op7_hnsw_neighbours,
    "op8_mix_sources": mixing.op8_mix_sources,
    "op9_best_fit_packing": packing.op9_best_fit_packing,
    "op10_quality_ordinal": quality.op10_quality_ordinal,
}
ORACLES = {"op3_warc_transactions": warc.OP3_SQL, "op4_line_run_dedup": line_dedup.OP4_SQL, "op8_mix_sources": mixing.OP8_SQL}
