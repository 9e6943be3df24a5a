"""A corpus pipeline: reject low quality, drop near-duplicates, cut repeated passages, pack.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes what a stage
returns as Parquet in the shared folder and reads it back as the next one's ``docs``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.llm import packing, quality, simhash, substring
from binflow.storage import materialise, table


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, learned from the labels of these documents, does not reject (score of 0.5 or more).

    Rows with null ids, null, empty or very long texts are scored like others; repeated rows
    are kept or dropped alike; without usable labels the prior decides for all. All columns
    are passed on, whatever their names; an empty table stays empty.
    """
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.score(docs, model, keep=True)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, that with the smallest id.

    Null, empty and blank texts are one group; of repeated rows with one id one stays; a row
    without id stays only if its whole group has none, one row a group. All columns are
    passed on; an empty table stays empty.
    """
    return simhash.keep_one(docs)


def passage_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, without passages that an earlier one holds; n_chars follows the text.

    "Earlier" is a smaller id. Null, empty and short texts and rows without id stay as they
    are; null n_chars stay null. All columns are passed on; an empty table stays empty.
    """
    out = substring.remove_repeated(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_chars").isNotNull(), F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their places in sequences.

    Null and empty texts are the end id alone; repeated rows are packed each on their own;
    longer texts are cut; an empty table gives no rows.
    """
    return packing.pack(docs)


STAGES = [("quality", quality_filter), ("near_dedup", near_dedup), ("substring_dedup", passage_dedup), ("packing", pack_sequences)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; returns the rows of the last one."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
