"""Packing without crossing documents: power-of-two decomposition.

A document of n units is cut into whole pieces of ``2**max_log2`` units and then
one piece for each set bit of the rest, longest first.  Pieces of one length form
a bucket, so batches have a fixed shape and no sequence holds two documents.
Each task gives its pieces bucket by bucket, longest first, so that equal lengths lie together in every file
without a shuffle; ``write.partitionBy("bucket")`` makes a folder of each.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.bpe import VOCABULARY, Bpe
from textredun.llm.common import kept

SCHEMA = "doc_id bigint, piece_no int, start bigint, length bigint, bucket int, piece string"
MAX_LOG2 = 13


def binary_pieces(n: int, max_log2: int = MAX_LOG2) -> list[tuple[int, int]]:
    """(start, log2 length) of the pieces of n units, in order."""
    whole = n >> max_log2
    out = [(i << max_log2, max_log2) for i in range(whole)]
    out += [((n >> (b + 1)) << (b + 1), b) for b in range(max_log2 - 1, -1, -1) if n >> b & 1]
    return out


def _emit(batches, slicer, arrow_type, max_log2: int, flush: int = 20_000, units: int = 4_000_000):
    names = ["doc_id", "piece_no", "start", "length", "bucket", "piece"]
    types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), arrow_type]

    def batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(zip(*rows), types)], names)

    for b in batches:
        rows: list[tuple] = []
        held = 0
        for key, value in zip(b.column(0).to_pylist(), slicer(b.column(1))):
            if value is None:
                continue
            for no, (start, log2) in enumerate(binary_pieces(len(value), max_log2)):
                rows.append((key, no, start, 1 << log2, log2, value[start : start + (1 << log2)]))
                held += 1 << log2
                if len(rows) >= flush or held > units:
                    yield batch(rows)
                    rows, held = [], 0
        if rows:
            yield batch(rows)


def pack_text(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_log2: int = MAX_LOG2) -> DataFrame:
    """One row per piece of each text, in code points: ``doc_id, piece_no, start, length, bucket, piece``.

    ``length`` is ``2**bucket``; the pieces of a document, by ``piece_no``, join to its
    text.  NULL and empty texts give no pieces; a text of any length is cut whole.
    Rows with a NULL or repeated id are packed like any other.  An empty table gives
    an empty table; other columns are ignored.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    return _by_bucket(rows.mapInArrow(lambda it: _emit(it, lambda c: c.to_pylist(), pa.string(), max_log2), SCHEMA))


def pack_tokens(docs: DataFrame, id_col: str = "doc_id", token_col: str = "tokens", max_log2: int = MAX_LOG2) -> DataFrame:
    """As ``pack_text`` over an array<int> of token ids; ``piece`` is then such an array."""
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{token_col}`").alias("tokens"))

    def arrays(column):
        values, ends = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
        valid = column.is_valid().to_pylist()
        return (values[ends[i] : ends[i + 1]] if ok else None for i, ok in enumerate(valid))

    return _by_bucket(rows.mapInArrow(lambda it: _emit(it, arrays, pa.list_(pa.int32()), max_log2), SCHEMA.replace("piece string", "piece array<int>")))


def pack_encoded(docs: DataFrame, vocabulary: str = VOCABULARY, id_col: str = "doc_id", text_col: str = "text", max_log2: int = MAX_LOG2, cache: int = 200_000) -> DataFrame:
    """As ``pack_tokens`` over the tokens of each text (``bpe.encode``), encoded and cut in one step, so one worker a core does both.

    ``cache`` is how many pre-tokens a worker remembers.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    ranks = docs.sparkSession.sparkContext.broadcast(Bpe.load(vocabulary).ranks)

    def run(batches):
        bpe = kept(("bpe", vocabulary, cache), lambda: Bpe(ranks.value, cache=cache))
        tokens = lambda texts: (None if t is None else bpe.encode_array(t) for t in texts.to_pylist())
        yield from _emit((b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)), tokens, pa.list_(pa.int32()), max_log2)

    return _by_bucket(rows.mapInArrow(run, SCHEMA.replace("piece string", "piece array<int>")))


def _by_bucket(pieces: DataFrame) -> DataFrame:
    """Equal lengths next to one another within each task: an external sort on a small key, no exchange."""
    return pieces.sortWithinPartitions(F.desc("bucket"))


def bucket_totals(pieces: DataFrame, tokens_per_batch: int = 1 << 19) -> DataFrame:
    """Per bucket: sequences, units, sequences to a batch of ``tokens_per_batch`` units and whole batches."""
    return (
        pieces.groupBy("bucket")
        .agg(F.count(F.lit(1)).alias("n_sequences"), F.sum("length").alias("n_units"))
        .withColumn("per_batch", F.greatest(F.lit(1), F.floor(F.lit(tokens_per_batch) / F.pow(F.lit(2.0), F.col("bucket")))).cast("bigint"))
        .withColumn("n_batches", F.floor(F.col("n_sequences") / F.col("per_batch")))
    )
