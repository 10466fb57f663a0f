"""Queries of this subpackage, by the names under which the entry module registers them."""

from __future__ import annotations

from . import forest, language, lines, minhash, mixing, packing, pseudonyms, repetition, sharding, toxicity

QUERIES = {
    "op1_random_projection_forest": forest.query,
    "op2_circulant_minhash": minhash.query,
    "op3_feistel_pseudonyms": pseudonyms.query,
    "op4_source_mixing": mixing.query,
    "op5_label_propagation_sharding": sharding.query,
    "op6_suffix_array_repetition": repetition.query,
    "op7_line_deletion_neighbourhood": lines.query,
    "op8_language_field": language.query,
    "op9_vector_best_fit_packing": packing.query,
    "op10_counterfactual_toxicity": toxicity.query,
}

ORACLE_SQL = {"op4_source_mixing": mixing.ORACLE_SQL}
