"""Registered queries of the text operators, and the SQL that some of them can be stated in."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from driftrank.llm import class_lm, decontaminate, fingerprint, jaccard_join, licenses, pieces, substring_dedup, token_store, toxicity, url_filter


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "op1_toxicity": toxicity.op1_toxicity,
        "op2_decontaminate": decontaminate.op2_decontaminate,
        "op3_class_lm": class_lm.op3_class_lm,
        "op4_substring_dedup": substring_dedup.op4_substring_dedup,
        "op5_url_filter": url_filter.op5_url_filter,
        "op6_token_files": token_store.op6_token_files,
        "op7_jaccard_join": jaccard_join.op7_jaccard_join,
        "op8_fingerprint": fingerprint.op8_fingerprint,
        "op9_pieces": pieces.op9_pieces,
        "op10_licenses": licenses.op10_licenses,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {}
