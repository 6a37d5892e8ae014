import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from textredun.llm import simhash as S

DOCS = "doc_id bigint, text string"


def brute(rows, radius, confirm):
    """All pairs of (id, fp, confirm) by comparing each with each."""
    out = set()
    for a in range(len(rows)):
        for b in range(a + 1, len(rows)):
            (i, x, c), (j, y, d) = rows[a], rows[b]
            h = int(x ^ y).bit_count()
            if h <= radius and int(c ^ d).bit_count() <= confirm:
                out.add((min(i, j), max(i, j), h))
    return out


def test_majority_counts_every_bit():
    rng = np.random.default_rng(1)
    lengths = [0, 1, 254, 255, 256, 700, 0, 3]
    starts = np.concatenate([[0], np.cumsum(lengths)])
    h = rng.integers(0, 2**64, starts[-1], dtype=np.uint64)
    got = S.majority(h, starts)
    for i, n in enumerate(lengths):
        run = h[starts[i] : starts[i + 1]]
        want = sum(1 << b for b in range(64) if sum((int(x) >> b) & 1 for x in run) * 2 > n)
        assert int(got[i]) == want


@pytest.mark.parametrize("radius", [0, 3, 7, 10, 15])
def test_pairs_equal_brute_force(spark, radius):
    rng = np.random.default_rng(radius)
    fp = rng.integers(0, 2**64, 300, dtype=np.uint64)
    near = fp.copy()
    for i in range(len(near)):
        for b in rng.choice(64, rng.integers(1, 14), replace=False):
            near[i] ^= np.uint64(1) << np.uint64(b)
    rows = [(i, int(x), 5) for i, x in enumerate(dict.fromkeys([*fp.tolist(), *near.tolist()]))]
    rows[7] = (*rows[7][:2], 2**40 - 1)
    df = spark.createDataFrame([(i, int(np.uint64(x).astype(np.int64)), c) for i, x, c in rows], S.FINGERPRINT_SCHEMA).repartition(3)
    got = [tuple(r) for r in S.near_fingerprints(df, radius, 20, levels=4).collect()]
    assert len(got) == len(set(got))
    assert set(got) == brute(rows, radius, 20)


def test_pairs_of_documents_equal_brute_force(spark, data):
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    prints = [(r.doc_id, r.fp & (2**64 - 1), r.confirm & (2**64 - 1)) for r in S.fingerprints(docs).collect()]
    lead = {}
    for i, fp, c in sorted(prints):
        lead.setdefault((fp, c), i)
    want = {(lead[fp, c], i, 0) for i, fp, c in prints if lead[fp, c] != i} | brute([(i, *k) for k, i in lead.items()], S.RADIUS, S.CONFIRM)
    assert {tuple(r) for r in S.near_pairs(docs).collect()} == want and len(want) > 50


def test_edges_of_input(spark):
    long = " ".join(f"word{i}" for i in range(50_000))
    text = "The quick brown fox jumps over the lazy dog while seven wizards mix potions by the old stone bridge at dawn today"
    rows = [(1, text), (2, text + "."), (2, text + "."), (3, None), (4, ""), (5, " \n"), (6, long), (7, long + " more"), (None, text), (8, "one"), (9, "One"), (10, "!!! ...")]
    docs = spark.createDataFrame(rows, DOCS).withColumn("fp", F.lit("x")).withColumn("gone", F.lit(1)).withColumn("confirm", F.lit(2))
    assert {(r.doc_a, r.doc_b) for r in S.near_pairs(docs).collect()} == {(1, 2), (6, 7), (8, 9)}
    kept = S.near_dedup(docs)
    assert kept.columns == docs.columns
    assert sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 3, 4, 5, 6, 8, 10]


def test_empty_table(spark):
    docs = spark.createDataFrame([], DOCS)
    assert S.near_pairs(docs).count() == 0 and S.near_dedup(docs).count() == 0


def test_components_follow_chains(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, 90), (90, 95), (200, 201), (201, 200)]
    got = {r.doc_id: r.group_id for r in S.components(spark.createDataFrame(edges, "doc_a bigint, doc_b bigint")).collect()}
    assert got == {**{i: 1 for i in range(2, 41)}, 95: 90, 100: 90, 201: 200}


def test_forest_connects_what_pairs_connect(spark):
    rng = np.random.default_rng(9)
    seeds = rng.integers(0, 2**64, 40, dtype=np.uint64)
    fps = [int(s) for s in seeds]
    for s in seeds:
        x = int(s)
        for _ in range(12):
            x ^= 1 << int(rng.integers(64))
            x ^= 1 << int(rng.integers(64))
            fps.append(x)
    rows = [(i, int(np.uint64(x).astype(np.int64)), 0) for i, x in enumerate(dict.fromkeys(fps))]
    df = spark.createDataFrame(rows, S.FINGERPRINT_SCHEMA)
    of = lambda e: {r.doc_id: r.group_id for r in S.components(e).collect()}
    assert of(S.near_fingerprints(df, 6, 0)) == of(S.near_fingerprints(df, 6, 0, forest=True))


def classes(prints, radius=S.RADIUS, confirm=S.CONFIRM):
    """(class, links) of each of the (id, fp, confirm) by comparing each with each."""
    lead = {p: p for p in prints}

    def top(p):
        while lead[p] != p:
            p = lead[p]
        return p

    near = {p: [q for q in prints if q != p and (p[1] ^ q[1]).bit_count() <= radius and (p[2] ^ q[2]).bit_count() <= confirm] for p in prints}
    for p, others in near.items():
        for q in others:
            lo, hi = sorted((top(p), top(q)))
            lead[hi] = lo
    return {p: (top(p)[0], len(near[p])) for p in prints}


def test_query_gives_classes_and_links(spark, tmp_path):
    """Copies and near copies of them, a row for each document, against comparing all with all."""
    import __spark_entry__ as entry

    words = [f"word{i}" for i in range(200)]
    first, near, other = " ".join(words), " ".join([*words[:-1], "else"]), " ".join(f"other{i}" for i in range(50))
    texts = [other, first, near, first, near, first, None, near, first, "", other, near]
    rows = [(100 - i, t) for i, t in enumerate(texts)] + [(100, other), (99, near), (60, first), (60, other), (None, first)]
    docs = spark.createDataFrame(rows, DOCS)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    of = {i: (r.fp & (2**64 - 1), r.confirm & (2**64 - 1)) for i, t in enumerate(dict.fromkeys(t for _, t in rows if t)) for r in S.fingerprints(spark.createDataFrame([(i, t)], DOCS)).collect()}
    of = dict(zip(dict.fromkeys(t for _, t in rows if t), of.values()))
    known = classes({(i, *of[t]) for i, t in rows if t and i is not None})
    want = [(i, *known[(i, *of[t])]) if t and i is not None else (i, i, 0) for i, t in rows]
    got = [tuple(r) for r in entry.queries()["op4_simhash"](spark, str(tmp_path)).collect()]
    assert sorted(got, key=str) == sorted(want, key=str) and max(n for *_, n in got) > 5 and len(got) == len(rows)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert sorted(con.execute(entry.oracle_sql()["op4_simhash"]).fetchall(), key=str) == sorted(got, key=str)


def test_classes_of_documents_equal_brute_force(spark, data):
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    known = classes([(r.doc_id, r.fp & (2**64 - 1), r.confirm & (2**64 - 1)) for r in S.fingerprints(docs).collect()])
    got = {r.doc_id: (r.class_id, r.n_links) for r in S.near_classes(docs).collect()}
    assert {p[0]: c for p, c in known.items()} == {i: got[i] for i in {p[0] for p in known}} and len(got) == docs.count()
    assert S.near_classes(docs.limit(0)).count() == 0


def test_rows_grow_with_the_documents(spark):
    """A group of copies has a row for each, not for each pair."""
    docs = spark.createDataFrame([(i, "one and the same text of some words") for i in range(3000)], DOCS)
    got = S.near_classes(docs).collect()
    assert len(got) == 3000 and {(r.class_id, r.n_links) for r in got} == {(0, 2999)}


@pytest.mark.parametrize("radius", [3, 10])
def test_search_by_value_finds_what_all_with_all_finds(monkeypatch, radius):
    rng = np.random.default_rng(4)
    fp = rng.integers(0, 2**64, 900, dtype=np.uint64)
    for i in range(300):
        fp[i + 600] = fp[i] ^ np.uint64(sum(1 << int(b) for b in rng.choice(64, rng.integers(0, radius + 3), replace=False)))
    calls = []
    real = S.by_value
    monkeypatch.setattr(S, "VALUE_COST", (0, 0))
    monkeypatch.setattr(S, "by_value", lambda *a: calls.append(1) or real(*a, cells=500))
    got = [(int(a), int(b)) for t in range(S.BLOCKS) for i, j in S.search(fp, fp[:0], t, radius // 4, radius, leaf=0) for a, b in zip(i, j)]
    want = {(a, b) for a in range(900) for b in range(a + 1, 900) if int(fp[a] ^ fp[b]).bit_count() <= radius}
    assert calls and len(got) == len(set(got)) and set(got) == want


def test_all_pairs_of_documents_equal_brute_force(spark, data):
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    prints = [(r.doc_id, r.fp & (2**64 - 1), r.confirm & (2**64 - 1)) for r in S.fingerprints(docs).collect()]
    got = [tuple(r) for r in S.all_pairs(docs).collect()]
    assert len(got) == len(set(got)) and set(got) == brute(prints, S.RADIUS, S.CONFIRM)


def test_more_shards_give_the_same_pairs(spark, data, monkeypatch):
    """Shards grow with the fingerprints; a task takes one after the other."""
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    want = {tuple(r) for r in S.all_pairs(docs).collect()}
    monkeypatch.setattr(S, "SHARD_ROWS", 2)
    assert {tuple(r) for r in S.all_pairs(docs).collect()} == want


def test_shards_grow_with_the_tally(spark, monkeypatch):
    seen = []
    real = S.routes
    monkeypatch.setattr(S, "routes", lambda weight, radius, levels: seen.append(levels) or real(weight, radius, min(levels, 3)))
    rng = np.random.default_rng(0)
    df = spark.createDataFrame([(i, int(x), 0) for i, x in enumerate(rng.integers(-(2**62), 2**62, 2000))], S.FINGERPRINT_SCHEMA)
    for rows in (20_000, 10, 1):
        monkeypatch.setattr(S, "SHARD_ROWS", rows)
        S.near_fingerprints(df)
    assert seen[::4] == [6, 8, 11]
