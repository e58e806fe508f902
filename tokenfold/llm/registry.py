"""The queries of this subpackage and their DuckDB texts."""

from __future__ import annotations

from . import cgk_decontamination, chosen_path, compression_bands, cotraining, licence_scan, line_dedup, packing, piece_counts, sharding, sparse_suffixes

_OPERATORS = (
    packing.op1_bm25_packing,
    line_dedup.op2_line_dedup,
    cgk_decontamination.op3_cgk_decontamination,
    compression_bands.op4_compression_bands,
    chosen_path.op5_chosen_path_join,
    cotraining.op6_cotraining,
    sparse_suffixes.op7_sparse_suffixes,
    piece_counts.op8_viterbi_counts,
    licence_scan.op9_licence_dice,
    sharding.op10_byte_prefix_shards,
)


def queries() -> dict:
    return {f.__name__: f for f in _OPERATORS}


def oracle_sql() -> dict[str, str]:
    return {"op2_line_dedup": line_dedup.OP2_SQL}
