import random

from pyspark.sql import functions as F

from textredun.llm import bpe, packing
from textredun.llm.sharding import assign_shards, shard_sizes

DOCS = "doc_id bigint, text string"


def test_shards_are_contiguous_and_balanced(spark):
    rng = random.Random(3)
    rows = [(i, "é" * rng.randint(0, 400)) for i in rng.sample(range(10_000), 1500)]
    out = sorted((r.doc_id, r.n_bytes, r.byte_start, r.shard_id) for r in assign_shards(spark.createDataFrame(rows, DOCS).repartition(5), 16).collect())
    at, total = 0, sum(2 * len(t) for _, t in rows)
    for (_, text), (_, n, start, shard) in zip(sorted(rows), out):
        assert (n, start, shard) == (2 * len(text), at, min(at // -(-total // 16), 15))
        at += n
    sizes = [r.n_bytes for r in shard_sizes(assign_shards(spark.createDataFrame(rows, DOCS), 16)).collect()]
    assert len(sizes) == 16 and max(sizes) < total / 16 + 800


def test_sharding_edges(spark):
    rows = [(2, "bb"), (None, "a"), (1, None), (2, "bb"), (2, "c"), (3, ""), (4, "d" * 200_000)]
    df = spark.createDataFrame(rows, DOCS).withColumn("n_bytes", F.lit("x")).withColumn("part", F.lit(0))
    got = sorted(((r.doc_id or 0, r.n_bytes, r.byte_start, r.shard_id) for r in assign_shards(df, 2).collect()))
    assert got == [(0, 1, 0, 0), (1, 0, 1, 0), (2, 1, 1, 0), (2, 2, 2, 0), (2, 2, 4, 0), (3, 0, 6, 0), (4, 200_000, 6, 0)]
    assert assign_shards(df.limit(0)).count() == 0
    assert {r.shard_id for r in assign_shards(df.where("text = '' OR text IS NULL")).collect()} == {0}


def test_binary_pieces_cover_every_length():
    for n in [*range(70), 8191, 8192, 8193, 100_000]:
        cut = packing.binary_pieces(n)
        at = 0
        for start, log2 in cut:
            assert start == at and log2 <= packing.MAX_LOG2
            at += 1 << log2
        assert at == n and [c[1] for c in cut] == sorted((c[1] for c in cut), reverse=True)


def test_pieces_join_to_their_text(spark):
    rows = [(1, "héllo wörld 🙂" * 999), (2, ""), (3, None), (4, "x" * 100_000), (None, "abc"), (5, "a"), (5, "a")]
    df = spark.createDataFrame(rows, DOCS).withColumn("piece", F.lit(1)).withColumn("bucket", F.lit(2))
    out = packing.pack_text(df)
    got: dict = {}
    for r in sorted(out.collect(), key=lambda r: (r.doc_id or 0, r.piece_no)):
        assert r.length == len(r.piece) == 1 << r.bucket
        got[r.doc_id] = got.get(r.doc_id, "") + r.piece
    assert got == {1: rows[0][1], 4: rows[3][1], None: "abc", 5: "aa"}
    assert packing.pack_text(df.limit(0)).count() == 0
    totals = {r.bucket: (r.n_sequences, r.per_batch, r.n_batches) for r in packing.bucket_totals(out, 16384).collect()}
    assert totals[13] == (sum(len(t or "") >> 13 for _, t in rows), 2, sum(len(t or "") >> 13 for _, t in rows) // 2)


def test_token_arrays_are_packed_alike(spark):
    rows = [(1, list(range(1000))), (2, []), (3, None), (4, [7])]
    out = packing.pack_tokens(spark.createDataFrame(rows, "doc_id bigint, tokens array<int>"), max_log2=8).collect()
    assert sum((list(r.piece) for r in sorted((r for r in out if r.doc_id == 1), key=lambda r: r.piece_no)), []) == list(range(1000))
    assert {r.doc_id for r in out} == {1, 4} and all(len(r.piece) == r.length <= 256 for r in out)


def test_encoding_and_packing_in_one_step(spark, data):
    """As encoding first and packing its tokens after."""
    docs = spark.read.parquet(data("0.001") + "/documents.parquet").unionByName(spark.createDataFrame([(None, "a b", "x", "x", 1), (5, None, "x", "x", 1), (6, "", "x", "x", 0)], "doc_id bigint, text string, lang string, source string, n_chars bigint"))
    docs = docs.withColumn("tokens", F.lit("x"))
    show = lambda df: sorted(map(str, df.collect()))
    one = packing.pack_encoded(docs)
    assert show(one) == show(packing.pack_tokens(bpe.encode(docs))) and one.count() > 500
    assert packing.pack_encoded(docs.limit(0)).count() == 0
    last = {}
    for part, bucket in one.select(F.spark_partition_id(), "bucket").collect():
        assert bucket <= last.get(part, 99)
        last[part] = bucket
