"""The queries of this subpackage and their SQL, for the driver's entry file."""

from __future__ import annotations

import corpus_pipeline
from vtask.llm import byte_bpe, edit_counts, exact_dedup, language_id, mixing, pii, png_media, quality, simhash, substring_dedup

QUERIES = {
    "op1_substring_dedup": substring_dedup.op1_substring_dedup,
    "op2_simhash_near_dedup": simhash.op2_simhash_near_dedup,
    "op3_mix_sources": mixing.op3_mix_sources,
    "op4_edit_token_counts": edit_counts.op4_edit_token_counts,
    "op5_pii": pii.op5_pii,
    "op6_png_media": png_media.op6_png_media,
    "op7_byte_bpe": byte_bpe.op7_byte_bpe,
    "op8_language_id": language_id.op8_language_id,
    "op9_exact_dedup": exact_dedup.op9_exact_dedup,
    "op10_quality_classifier": quality.op10_quality_classifier,
    "pipeline": corpus_pipeline.run,
}

ORACLE_SQL = {
    "op1_substring_dedup": substring_dedup.OP1_SQL,
    "op9_exact_dedup": exact_dedup.OP9_SQL,
}
if corpus_pipeline.ORACLE_SQL:
    ORACLE_SQL["pipeline"] = corpus_pipeline.ORACLE_SQL
