"""Queries of this subpackage and, where SQL can express them, their DuckDB equivalents."""

from __future__ import annotations

from idfold.llm import exact_dedup, hash_tree, line_dedup, mixing, piece_lattice, quality_rules, simhash_pivots, url_rules, warc_derive, weak_quality

QUERIES = {
    "op1_simhash_pivots": simhash_pivots.op1_simhash_pivots,
    "op2_weak_label_classifier": weak_quality.op2_weak_label_classifier,
    "op3_risk_controlled_rules": quality_rules.op3_risk_controlled_rules,
    "op4_raked_mixing": mixing.op4_raked_mixing,
    "op5_winnowed_lines": line_dedup.op5_winnowed_lines,
    "op6_hash_tree_sharding": hash_tree.op6_hash_tree_sharding,
    "op7_exact_dedup": exact_dedup.op7_exact_dedup,
    "op8_warc_derivatives": warc_derive.op8_warc_derivatives,
    "op9_piece_lattice": piece_lattice.op9_piece_lattice,
    "op10_url_range_join": url_rules.op10_url_range_join,
    "lattice_viterbi": piece_lattice.lattice_viterbi,
}

ORACLES = {
    "op3_risk_controlled_rules": quality_rules.oracle(),
    "op6_hash_tree_sharding": hash_tree.oracle(),
    "op4_raked_mixing": mixing.oracle(),
    "op7_exact_dedup": exact_dedup.SQL,
    "op10_url_range_join": url_rules.SQL,
}
