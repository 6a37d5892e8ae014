"""A training corpus from raw documents: drop toxic and poor ones, then copies and near copies, and pack the rest.

Every stage takes ``(spark, docs, sf_dir)``; its result is written as Parquet and read again as
the next one's ``docs``.  All stages but the last return the columns of ``documents``.
Classifiers learn from the labelled documents of ``sf_dir`` and judge ``docs``.

In every stage texts of any length are read whole, an empty table gives an empty table, and other columns of
``docs`` come back unchanged, whatever their names (but in packing, whose columns are its own).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from textredun.llm import exact_dedup, packing, quality, simhash, toxicity
from textredun.llm.common import documents, labels
from textredun.sources.shared import fresh_path


def toxic_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose sentences together don't pass the toxicity threshold. NULL and empty texts stay; rows that share an id are judged each by its text."""
    return toxicity.drop_toxic(docs, toxicity.train(documents(spark, sf_dir), labels(spark, sf_dir)))


def poor_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality trees keep. NULL texts go, empty ones are judged like any other; so is each row of a repeated or NULL id."""
    return quality.quality_filter(docs, quality.train(documents(spark, sf_dir), labels(spark, sf_dir)))


def copies_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each set of copies: that with the smallest id, NULL counting as the largest. Rows with a NULL text stay."""
    return exact_dedup.exact_dedup(docs)


def near_copies_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies, that with the smallest id. Rows without an id, text or word stay; so do rows that repeat the id that stays."""
    return simhash.near_dedup(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Power-of-two sequences of tokens, none of which crosses documents. NULL and empty texts give none; rows with a NULL or repeated id are packed like any other."""
    return packing.pack_encoded(docs)


STAGES = [
    ("toxicity", toxic_out),
    ("quality rules", poor_out),
    ("exact dedup", copies_out),
    ("near dedup", near_copies_out),
    ("packing", packed),
]

#: Trained classifiers and fingerprints have no SQL twin; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows over ``documents``; the stages' tables go to the session's shared folder, and each is read once."""
    docs, last = documents(spark, sf_dir), len(STAGES) - 1
    for i, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if i == last:
            return out
        path = fresh_path(spark, f"pipeline-{i}")
        out.write.parquet(path)
        docs = spark.read.schema(out.schema).parquet(path)
    return docs
