"""Exact deduplication by content sort.

Rows are range-partitioned on splitters that Spark samples from a short sort key
(a bounded prefix of the normalised bytes, then their 64-bit digest, so that a
prefix shared by much of the corpus still splits), sorted externally inside each
partition by that key, the full normalised bytes and the identifier, and every
row is compared in full with the neighbour before it.  One shuffle; everything
stays in the JVM.  The samples sent to the driver are short keys, never texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from textredun.llm.common import fresh

PREFIX_CHARS = 24


def normalised(text: Column) -> Column:
    """Line ends as ``\\n``; blanks, tabs and line ends at both ends removed."""
    lines = F.replace(F.replace(text, F.lit("\r\n"), F.lit("\n")), F.lit("\r"), F.lit("\n"))
    return F.btrim(lines, F.lit(" \t\n"))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay: of rows with equal normalised bytes, the one with the smallest id.

    Nulls: a row with a NULL text has no content to compare and stays; a NULL id
    counts as the largest, so any identified copy wins over it.  Empty texts
    equal each other (and texts of blanks only).  Rows that repeat with the same
    id are copies: one stays.  Texts of any length are compared whole.  An empty table gives an empty table.  All columns
    come back unchanged, whatever their names.
    """
    norm, key, prefix, changed, before = fresh(docs, "norm", "digest", "prefix", "changed", "before")
    text = F.col(f"`{text_col}`")
    rows = docs.withColumn(norm, normalised(text))
    # The text is carried once: beside its normalised form only where the two differ.
    rows = rows.select(
        *[F.col(f"`{c}`") for c in docs.columns if c != text_col],
        F.when(text != F.col(norm), text).alias(changed),
        F.col(norm),
        F.substring(norm, 1, PREFIX_CHARS).alias(prefix),
        F.when(text.isNull(), F.xxhash64(F.col(f"`{id_col}`"))).otherwise(F.xxhash64(norm)).alias(key),
    )
    same_key = Window.partitionBy(prefix, key).orderBy(F.col(norm), F.col(f"`{id_col}`").asc_nulls_last())
    kept = (
        rows.repartitionByRange(prefix, key)
        .withColumn(before, F.lag(norm).over(same_key))
        .where(F.col(norm).isNull() | F.col(before).isNull() | (F.col(norm) != F.col(before)))
    )
    restored = F.coalesce(F.col(changed), F.col(norm)).alias(text_col)
    return kept.select(*[restored if c == text_col else F.col(f"`{c}`") for c in docs.columns])
