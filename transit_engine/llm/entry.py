"""Queries and oracle texts of this subpackage for the driver's contract."""

from __future__ import annotations

from . import curriculum_mix, hnsw, itq_neardup, language_id, line_dedup, piece_lattice, recompression, simhash_vptree, suffix_array, toxicity

QUERIES = {
    "op1_itq_neardup": itq_neardup.op1_itq_neardup,
    "op2_suffix_array": suffix_array.op2_suffix_array,
    "op3_hnsw": hnsw.op3_hnsw,
    "op4_line_dedup": line_dedup.op4_line_dedup,
    "op5_piece_lattice": piece_lattice.op5_piece_lattice,
    "op6_language_id": language_id.op6_language_id,
    "op7_recompression": recompression.op7_recompression,
    "op8_simhash_vptree": simhash_vptree.op8_simhash_vptree,
    "op9_toxicity": toxicity.op9_toxicity,
    "op10_curriculum_mix": curriculum_mix.op10_curriculum_mix,
}

ORACLES = {
    "op4_line_dedup": line_dedup.ORACLE,
    "op10_curriculum_mix": curriculum_mix.ORACLE,
}
