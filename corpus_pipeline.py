"""Cleaning pipeline over ``documents``: each stage is written as Parquet and reread as the next one's input."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftrank.llm import decontaminate, jaccard_join, pieces, substring_dedup, toxicity
from driftrank.llm import words as W


def _plain(docs: DataFrame) -> DataFrame:
    """``docs`` with names that no operator makes: doc_id and text keep theirs, the others go by place."""
    return docs.toDF(*(c if c in ("doc_id", "text") else f"column_{i}" for i, c in enumerate(docs.columns)))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted on labelled rows, scores under 0.7, with all their columns.

    Null and empty texts score the prior, 0.5 at most, and stay; repeated rows share their fate; of no rows none stay.
    """
    model = toxicity.train(docs.select("doc_id", "text"), W.docs(spark, sf_dir, "labels"), F.lit(True))
    own = _plain(docs)
    return toxicity.score(own, model).where("toxic_score < 0.7").select(*own.columns).toDF(*docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five-word shingles, Jaccard 0.8 or more) the row with the least doc_id.

    Rows without words or without a doc_id have no group and stay, and so do all rows that share the least doc_id of a group.
    """
    classes = jaccard_join.jaccard_classes(docs.select("doc_id", "text"), k=5, percent=80)
    lost = classes.where("n_shingles > 0 and doc_id <> component_id").select("doc_id").distinct()
    return docs.join(lost, "doc_id", "left_anti").select(*docs.columns)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the words of repeated 35-word windows; n_chars, if there is one, follows the text.

    Texts that lose nothing stay as they are, null and empty ones too. Repeated rows repeat each other, so their common
    windows of 35 words go from all of them.
    """
    own = _plain(docs)
    others = [c for c in own.columns if c not in ("doc_id", "text")]
    kept = substring_dedup.dedup_substrings(own.withColumn("whole", F.col("text")), carry=[*others, "whole"])
    new = {"text": F.coalesce("kept", "whole")}
    if "n_chars" in docs.columns:
        at = own.columns[docs.columns.index("n_chars")]
        new[at] = F.when(F.col("kept").isNull(), F.col(at)).otherwise(F.length("kept")).cast(docs.schema["n_chars"].dataType)
    return kept.withColumns(new).select(*own.columns).toDF(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item. Null and empty texts hold none; rows without a doc_id stay."""
    leaks = decontaminate.find_leaks(docs.select("doc_id", "text"), W.docs(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.join(leaks, "doc_id", "left_anti").select(*docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each kept document's doc_id and best piece segmentation (packed ids, which decode_documents() turns into its text)."""
    return pieces.encode_documents(docs.select("doc_id", "text"))


STAGES = [
    ("toxicity", drop_toxic),
    ("jaccard_join", one_of_each_group),
    ("substring_dedup", cut_repeats),
    ("decontamination", drop_leaks),
    ("pieces", encode),
]
ORACLE_SQL = None  # no stage of these can be stated in SQL; tests/llm/test_queries.py holds the stages against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = W.docs(spark, sf_dir), None
    for name, stage in STAGES:
        docs = W.written(stage(spark, docs, sf_dir), f"stage-{name}")
        if last is not None:
            W.dropped(last)
        last = docs
    return docs
