"""Queries and DuckDB SQL of the training-data operators."""

from __future__ import annotations

import corpus_pipeline

from . import decontamination, fingerprints, jaccard, language, lm_scores, packing, passages, quality, secrets, toxicity


def queries() -> dict:
    return {
        "op1_quality": quality.op1_quality,
        "op2_packing": packing.op2_packing,
        "op3_fingerprints": fingerprints.op3_fingerprints,
        "op4_jaccard_join": jaccard.op4_jaccard_join,
        "op5_language": language.op5_language,
        "op6_lm_scores": lm_scores.op6_lm_scores,
        "op7_secrets": secrets.op7_secrets,
        "op8_decontamination": decontamination.op8_decontamination,
        "op9_substring_dedup": passages.op9_substring_dedup,
        "pipeline": corpus_pipeline.run,
        "op10_toxicity": toxicity.op10_toxicity,
    }


def oracle_sql() -> dict:
    return {"op4_jaccard_join": jaccard.OP4_SQL, "op7_secrets": secrets.OP7_SQL, "op8_decontamination": decontamination.OP8_SQL}
