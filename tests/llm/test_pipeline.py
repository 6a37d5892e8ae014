import hashlib
import re

import pytest
import tiktoken
from pyspark.sql import functions as F
from test_quality import plain as plain_statistics
from test_quality import walk
from test_toxicity import plain_rows

import corpus_pipeline as P
from textredun.llm import bpe, quality, queries, simhash, toxicity
from textredun.llm.common import documents, labels


def plain(text):
    return text.replace("\r\n", "\n").replace("\r", "\n").strip(" \t\n")


def mixed(x):
    x = (x ^ (x >> 30)) * 0xBF58476D1CE4E5B9 % 2**64
    x = (x ^ (x >> 27)) * 0x94D049BB133111EB % 2**64
    return x ^ (x >> 31)


def vote(hashes):
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def prints(text):
    """Both fingerprints of a text, bit by bit; None without a word."""
    words = re.findall(r"\w+", text.lower())
    h = [int(hashlib.md5(w.encode()).hexdigest()[:16], 16) for w in words]
    pairs = [mixed((a * 0x9E3779B97F4A7C15 + b) % 2**64) for a, b in zip(h, h[1:])] or [mixed(x) for x in h]
    return (vote(set(h)), vote(pairs)) if h else None


def pieces(n):
    at = 0
    for b in [13] * (n >> 13) + [b for b in range(12, -1, -1) if n >> b & 1]:
        yield at, b
        at += 1 << b


def one_by_one(spark, d):
    """The stages with plain loops over all documents; only the trained weights and trees come from the library."""
    rows = {r.doc_id: r.text for r in documents(spark, d).collect()}
    tox = toxicity.train(documents(spark, d), labels(spark, d))
    rows = {i: t for i, t in rows.items() if not plain_rows(tox, i, t)}
    trees = quality.train(documents(spark, d), labels(spark, d))
    rows = {i: t for i, t in rows.items() if walk(trees, plain_statistics(t)) >= trees.threshold}
    first: dict = {}
    for i in sorted(rows):
        first.setdefault(plain(rows[i]), i)
    rows = {i: rows[i] for i in first.values()}
    known = {i: x for i, t in rows.items() if (x := prints(t))}
    group = {i: i for i in rows}

    def top(i):
        while group[i] != i:
            i = group[i]
        return i

    ids = sorted(known)
    for x, i in enumerate(ids):
        for j in ids[x + 1 :]:
            (a, b), (c, e) = known[i], known[j]
            if (a ^ c).bit_count() <= simhash.RADIUS and (b ^ e).bit_count() <= simhash.CONFIRM:
                lo, hi = sorted((top(i), top(j)))
                group[hi] = lo
    coder = tiktoken.Encoding("own", pat_str=bpe.PRE_TOKEN, mergeable_ranks=bpe.Bpe.load().ranks, special_tokens={})
    tokens = {i: coder.encode(t, disallowed_special=()) for i, t in rows.items() if top(i) == i}
    return sorted((i, no, s, 1 << b, b, t[s : s + (1 << b)]) for i, t in tokens.items() for no, (s, b) in enumerate(pieces(len(t))))


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_run_equals_plain_loops(spark, data, sf):
    got = sorted(map(tuple, P.run(spark, data(sf)).collect()))
    want = one_by_one(spark, data(sf))
    assert got == want and len(got) > 100


def test_stages_keep_the_columns_of_documents(spark, data):
    docs = documents(spark, data("0.001"))
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, data("0.001"))
        assert out.columns == docs.columns and 0 < out.count() <= docs.count(), name
    assert P.ORACLE_SQL is None


def test_stages_take_empty_tables_and_nulls(spark, data):
    docs = documents(spark, data("0.001"))
    odd = docs.limit(0).unionByName(spark.createDataFrame([(None, None, None, None, None), (1, None, "en", "s", None), (1, "", None, None, 0)], docs.schema))
    for name, stage in P.STAGES:
        assert stage(spark, docs.limit(0), data("0.001")).count() == 0, name
        stage(spark, odd, data("0.001")).count()


def test_stages_take_long_repeated_and_clashing_rows(spark, data):
    """Whole rows that repeat, a very long text, and columns named like those that the operators make."""
    d = data("0.001")
    few = documents(spark, d).orderBy("doc_id").limit(20)
    long = few.limit(1).withColumns({"doc_id": F.lit(10_000).cast("bigint"), "text": F.repeat(F.concat("text", F.lit(" and so on, ")), 300)})
    names = ("toxicity", "quality_score", "norm", "digest", "prefix", "before", "changed", "gone", "other", "fp", "confirm", "tokens", "n_tokens", "piece", "scored", "y", "h")
    docs = few.unionByName(few).unionByName(long).withColumns({c: F.lit(c) for c in names})
    left = {}
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, d)
        assert out.columns == docs.columns, name
        rows = out.collect()
        assert all(r[c] == c for r in rows for c in names), name
        left[name] = sorted(r.doc_id for r in rows)
    judged = [sorted(set(left[k]) - {10_000}) for k in ("toxicity", "quality rules")]
    assert all(sorted(j * 2) == [i for i in left[k] if i != 10_000] for j, k in zip(judged, ("toxicity", "quality rules"))) and 10_000 in left["toxicity"]
    assert len(left["exact dedup"]) == len(set(left["exact dedup"])) and 10_000 in left["exact dedup"]
    packed = P.packed(spark, docs, d)
    assert packed.columns == ["doc_id", "piece_no", "start", "length", "bucket", "piece"] and packed.where("doc_id = 10000").agg(F.max("bucket")).first()[0] == 13


def test_every_operator_has_one_query():
    names = sorted(queries.queries(), key=lambda n: int(n[2:].split("_")[0]))
    assert [n.split("_")[0] for n in names] == [f"op{i}" for i in (1, 2, 3, 4, 5, 6, 6, 7, 8, 9, 10)]  # op6_warc: the same as op6_warc_records, as SQL can say it
    assert set(queries.oracle_sql()) <= set(names)
