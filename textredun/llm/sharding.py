"""Contiguous shards of balanced byte size.

Only (id, byte length) leaves the scan: the pairs are range-partitioned and
sorted by id, checkpointed so that partition contents are fixed, and summed per
partition.  The partition totals (one row each) become global prefix sums, from
which every partition continues on its own: no text is shuffled and no second
exchange is needed.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import cut_lineage

SCHEMA = "doc_id bigint, n_bytes bigint, byte_start bigint, shard_id bigint"


def assign_shards(docs: DataFrame, n_shards: int = 64, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_bytes, byte_start, shard_id``.

    Documents are laid end to end in order of id; the byte axis is cut every
    ``ceil(total / n_shards)`` bytes and a document belongs to the shard in which
    it starts, so a shard exceeds the target by less than its last document.

    Nulls: a NULL text counts 0 bytes; NULL ids come first.  Rows that share an id
    are ordered by size, so the result does not depend on their order.  Documents
    of 0 bytes go where the next byte would; at the very end, to the last shard.
    An empty table, or one without any byte, has no cut: all rows go to shard 0.
    Texts of any length are measured whole.  Other columns, whatever their names, are ignored.
    """
    if n_shards < 1:
        raise ValueError("n_shards must be positive")
    sized = docs.select(
        F.col(f"`{id_col}`").cast("bigint").alias("doc_id"),
        F.coalesce(F.octet_length(F.col(f"`{text_col}`")).cast("bigint"), F.lit(0).cast("bigint")).alias("n_bytes"),
    )
    placed = cut_lineage(
        sized.repartitionByRange("doc_id", "n_bytes")
        .sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "n_bytes")
        .withColumn("part", F.spark_partition_id())
    )
    totals = placed.groupBy("part").agg(F.sum("n_bytes").alias("bytes")).orderBy("part").collect()
    starts = dict(zip((r["part"] for r in totals), itertools.accumulate((r["bytes"] for r in totals), initial=0)))
    total = sum(r["bytes"] for r in totals)
    target, last = max(1, -(-total // n_shards)), max(0, n_shards - 1)

    def place(batches):
        at = None
        for b in batches:
            if not b.num_rows:
                continue
            if at is None:
                at = starts[b.column("part")[0].as_py()]
            size = b.column("n_bytes").to_numpy()
            ends = at + np.cumsum(size)
            begin = ends - size
            at = int(ends[-1])
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("n_bytes"), pa.array(begin), pa.array(np.minimum(begin // target, last))],
                ["doc_id", "n_bytes", "byte_start", "shard_id"],
            )

    return placed.mapInArrow(place, SCHEMA)


def shard_sizes(assigned: DataFrame) -> DataFrame:
    """Documents, bytes and id range of each shard."""
    return assigned.groupBy("shard_id").agg(
        F.count(F.lit(1)).alias("n_docs"), F.sum("n_bytes").alias("n_bytes"), F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id")
    )
