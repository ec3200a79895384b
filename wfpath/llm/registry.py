"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from wfpath.llm import mixing, ngram_join, packing, substring_dedup, suffix_dedup, token_files, vector_dedup
from wfpath.llm.quality_model import op3_quality_model
from wfpath.llm.quality_rules import op2_quality_rules
from wfpath.llm.url_filter import op4_url_filter

QUERIES = {
    "op1_source_mix": mixing.op1_source_mix,
    "op2_quality_rules": op2_quality_rules,
    "op3_quality_model": op3_quality_model,
    "op4_url_filter": op4_url_filter,
    "op5_ngram_join": ngram_join.op5_ngram_join,
    "op6_token_files": token_files.op6_token_files,
    "op7_suffix_dedup": suffix_dedup.op7_suffix_dedup,
    "op8_best_fit_packing": packing.op8_best_fit_packing,
    "op9_vector_dedup": vector_dedup.op9_vector_dedup,
    "op10_substring_dedup": substring_dedup.op10_substring_dedup,
}
ORACLES: dict[str, str] = {"op1_source_mix": mixing.ORACLE}
