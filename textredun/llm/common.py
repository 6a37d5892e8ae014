"""Small helpers shared by the training-data operators."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import textredun.llm
from textredun.operators.kernel import kept  # noqa: F401
from textredun.sources.shared import shared_folder

# Kernels travel to the workers by value, so executors need no copy of the package.
cloudpickle.register_pickle_by_value(textredun.llm)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names derived from ``names`` that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def cut_lineage(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the session's shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def tasks_for(spark: SparkSession, pieces: int) -> int:
    """Tasks for so many pieces of work: one each, but no more than the session's shuffle partitions."""
    return max(1, min(pieces, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def offsets(lengths: Iterable[int]) -> np.ndarray:
    """[0, l0, l0+l1, ...] as int64."""
    lens = np.fromiter(lengths, dtype=np.int64)
    out = np.zeros(len(lens) + 1, dtype=np.int64)
    np.cumsum(lens, out=out[1:])
    return out


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of the splitmix64 generator: a bijection of uint64 that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Memo(dict):
    """word -> value cache that computes what is missing and starts anew beyond ``limit`` entries."""

    def __init__(self, compute, limit: int = 150_000):
        super().__init__()
        self.compute, self.limit = compute, limit

    def __missing__(self, key):
        if len(self) >= self.limit:
            self.clear()
        value = self[key] = self.compute(key)
        return value


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, least: int, id_col: str, text_col: str) -> DataFrame:
    """``doc_id, text, y`` of at most ``least`` documents of each of the classes 0 and 1 of a label column, for training.

    Drawn by a hash of the id among the labels that have a document, so the same on every run: labels
    without one take no place.  Of an id's labels the greatest counts, of its texts the first in order.
    NULL labels, ids and texts are left out.  Text is read for the ids drawn alone.
    """
    there = docs.select(F.col(f"`{id_col}`").alias("doc_id"))
    y = labels.select("doc_id", F.col(column).alias("y")).where("y IN (0, 1) AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("y").alias("y")).join(there, "doc_id", "left_semi")
    drawn = [y.where(F.col("y") == c).withColumn("h", F.xxhash64("doc_id")).orderBy("h", "doc_id").limit(least).drop("h") for c in (1, 0)]
    text = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).where("text IS NOT NULL")
    rows = text.join(F.broadcast(drawn[0].unionByName(drawn[1])), "doc_id")
    return rows.groupBy("doc_id", "y").agg(F.min("text").alias("text")).orderBy(F.xxhash64("doc_id"), "doc_id").select("doc_id", "text", "y")
