"""Queries of the ten operators and of the pipeline, with SQL where SQL can state their rows."""

from __future__ import annotations

from . import ann_graph, importance, jaccard_join, language_id, license_scan, lm_scoring, mixing, packing, quality_rules, surrogates


def queries() -> dict:
    return {
        "op1_license_scan": license_scan.query,
        "op2_pruned_graph_search": ann_graph.query,
        "op3_quality_rules": quality_rules.query,
        "op4_jaccard_join": jaccard_join.query,
        "op5_pii_surrogates": surrogates.query,
        "op6_temperature_mixing": mixing.query,
        "op7_best_fit_packing": packing.query,
        "op8_language_id": language_id.query,
        "op9_pitman_yor_scoring": lm_scoring.query,
        "op10_importance_resampling": importance.query,
    }


def oracle_sql() -> dict[str, str]:
    return {}
