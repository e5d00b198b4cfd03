"""Queries and DuckDB SQL of the training-data operators, for ``__spark_entry__``."""

from __future__ import annotations

import corpus_pipeline

from . import cotrain, decontaminate, licences, lm, pieces, quality_rules, repair, sharding, simhash, toxicity

QUERIES = {
    "pipeline": corpus_pipeline.run,
    "op1_suffix_array_pieces": pieces.query,
    "op2_decontaminate": decontaminate.query,
    "op3_simhash": simhash.query,
    "op4_robust_outliers": quality_rules.query,
    "op5_deleted_interpolation": lm.query,
    "op6_nnpu_toxicity": toxicity.query,
    "op7_best_fit_shards": sharding.query,
    "op8_repair_ids": repair.query,
    "op9_cotrain_quality": cotrain.query,
    "op10_licence_paragraphs": licences.query,
}

ORACLES: dict[str, str] = {
    "op2_decontaminate": decontaminate.ORACLE,
}
