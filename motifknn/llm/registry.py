"""Queries of this subpackage, for the entry module."""

from __future__ import annotations

from motifknn.llm.digest import op10_improbable_digest
from motifknn.llm.html import op4_html_main_text
from motifknn.llm.langid import op1_language_id
from motifknn.llm.lines import op7_fuzzy_line_dedup
from motifknn.llm.mixing import SQL_OP3, op3_curriculum_mix
from motifknn.llm.neardup import op9_minhash_near_dedup
from motifknn.llm.packing import op6_best_fit_packing
from motifknn.llm.quality import op2_distribution_quality
from motifknn.llm.sharding import op8_vector_bin_packing_shards
from motifknn.llm.tokens import op5_token_counts

QUERIES = {
    "op1_language_id": op1_language_id,
    "op2_distribution_quality": op2_distribution_quality,
    "op3_curriculum_mix": op3_curriculum_mix,
    "op4_html_main_text": op4_html_main_text,
    "op5_token_counts": op5_token_counts,
    "op6_best_fit_packing": op6_best_fit_packing,
    "op7_fuzzy_line_dedup": op7_fuzzy_line_dedup,
    "op8_vector_bin_packing_shards": op8_vector_bin_packing_shards,
    "op9_minhash_near_dedup": op9_minhash_near_dedup,
    "op10_improbable_digest": op10_improbable_digest,
}

SQL: dict[str, str] = {
    "op3_curriculum_mix": SQL_OP3,
}
