"""Registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from . import chat, exact_dedup, jaccard_join, langid, line_dedup, mixing, packing, quality, token_counts, toxicity


def pipeline(spark, sf_dir: str):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "pipeline": pipeline,
        "op1_distribution_divergence": quality.op1_distribution_divergence,
        "op2_token_counts": token_counts.op2_token_counts,
        "op3_exact_dedup": exact_dedup.op3_exact_dedup,
        "op4_chat_formatting": chat.op4_chat_formatting,
        "op5_mixing": mixing.op5_mixing,
        "op6_packing": packing.op6_packing,
        "op7_jaccard_join": jaccard_join.op7_jaccard_join,
        "op8_language_id": langid.op8_language_id,
        "op9_line_dedup": line_dedup.op9_line_dedup,
        "op10_toxicity": toxicity.op10_toxicity,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_distribution_divergence": quality.oracle(),
        "op3_exact_dedup": exact_dedup.ORACLE,
        "op5_mixing": mixing.oracle(),
        "op9_line_dedup": line_dedup.oracle(),
    }
