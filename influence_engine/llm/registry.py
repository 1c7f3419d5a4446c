"""Queries of this subpackage by name, and their SQL where SQL can express them."""

from __future__ import annotations

from . import (
    exact_dedup,
    language_id,
    mixing,
    multi_index,
    packing,
    sharding,
    simhash,
    substring_dedup,
    token_counts,
    token_output,
)

QUERIES = {
    "op1_mix_sources": mixing.op1_mix_sources,
    "op2_token_counts": token_counts.op2_token_counts,
    "op3_simhash": simhash.op3_simhash,
    "op4_substring_dedup": substring_dedup.op4_substring_dedup,
    "op5_wavelet_output": token_output.op5_wavelet_output,
    "op6_multi_index": multi_index.op6_multi_index,
    "op7_jump_sharding": sharding.op7_jump_sharding,
    "op8_best_fit_packing": packing.op8_best_fit_packing,
    "op9_language_id": language_id.op9_language_id,
    "op10_exact_dedup": exact_dedup.op10_exact_dedup,
}

ORACLE_SQL = {**exact_dedup.ORACLE_SQL, **substring_dedup.ORACLE_SQL, **sharding.ORACLE_SQL}
