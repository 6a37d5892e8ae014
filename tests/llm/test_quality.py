import tracemalloc
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from textredun.llm import quality as Q
from textredun.llm.common import documents, labels
from textredun.llm.queries import queries

DOCS = "doc_id bigint, text string"
STAT = list(Q.STATISTICS)


def walk(trees, row):
    """One row through the trees, node by node."""
    out = trees.base
    for feature, cut, leaf in zip(trees.feature, trees.cut, trees.leaf):
        node = 0
        while node < len(feature):
            node = 2 * node + (2 if row[feature[node]] > cut[node] else 1)
        out += leaf[node - len(feature)]
    return out


def sample(n=3000, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, 5))
    p = 1 / (1 + np.exp(-(2 * x[:, 0] - 2 * x[:, 1] + np.sin(3 * x[:, 2]))))
    return x, (rng.random(n) < p).astype(int)


def test_flat_arrays_score_like_a_walk():
    x, y = sample()
    trees = Q.fit(x, y, np.array([1, -1, 0, 0, 0]), n_trees=20)
    assert np.allclose(trees.score(x[:200]), [walk(trees, r) for r in x[:200]])
    assert ((trees.score(x) > 0) == y).mean() > 0.75


def test_signs_hold_everywhere():
    x, y = sample(seed=1)
    y[::7] = 1 - y[::7]
    trees = Q.fit(x, y, np.array([1, -1, 0, 0, 1]), n_trees=40)
    rng = np.random.default_rng(2)
    for column, sign in ((0, 1), (1, -1), (4, 1)):
        base = np.repeat(rng.normal(size=(200, 5)), 30, axis=0)
        base[:, column] = np.tile(np.linspace(-4, 4, 30), 200)
        steps = np.diff(trees.score(base).reshape(200, 30), axis=1) * sign
        assert steps.min() >= -1e-12
    free = Q.fit(x, y, np.zeros(5, int), n_trees=40)
    assert np.diff(free.score(base).reshape(200, 30), axis=1).min() < 0


def plain(t):
    """The statistics with strings and loops."""
    if not t:
        return [0.0] * len(STAT)
    words, lines, n = t.split(), [x for x in t.split("\n") if x], len(t)
    w = max(len(words), 1)
    kinds = [Q.kind_of(c) for c in t]
    share = lambda bit: sum(bool(k & bit) for k in kinds) / n
    has = lambda x, bit: any(Q.kind_of(c) & bit for c in x)

    def spread(x):
        return (np.mean(x), np.std(x) / max(np.mean(x), 1e-9)) if x else (0.0, 0.0)

    (mw, sw), (ml, sl) = spread([len(x) for x in words]), spread([len(x) for x in lines])
    pairs = list(zip(words, words[1:]))
    out = dict(
        log_chars=np.log1p(n), log_words=np.log1p(len(words)), mean_word=mw, word_spread=sw, long_words=sum(len(x) > 15 for x in words) / w, short_words=sum(len(x) < 4 for x in words) / w,
        bare_words=sum(not has(x, Q.LETTER) for x in words) / w, marked_words=sum(has(x, Q.SYMBOL) for x in words) / w, stutter=sum(a == b for a, b in pairs) / w,
        top_word=max(Counter(words).values(), default=0) / w, distinct_words=len(set(words)) / w**0.8, repeated_pairs=1 - len(set(pairs)) / len(pairs) if pairs else 0.0,
        symbols=share(Q.SYMBOL), doubled_marks=sum(a == b and bool(Q.kind_of(a) & (Q.MARK | Q.SYMBOL)) for a, b in zip(t, t[1:])) / w, punctuation=share(Q.MARK), digits=share(Q.DIGIT), capitals=share(Q.CAPITAL), blanks=share(Q.BLANK),
        entropy=-sum(c / n * np.log(c / n) for c in Counter(t).values()), mean_line=ml, line_spread=sl, repeated_lines=1 - len(set(lines)) / len(lines) if lines else 0.0,
    )
    return [out[k] for k in STAT]


TEXTS = ["Ab ab ab | c## D!!\nx\nx", "", " \n", "x", "\n\na", "🙂 été, Ünï — “so” 12½", "a\r\nb\r\n", "word " * 3000, "no end\n", "\n", "one two one two one two"]


def test_statistics_equal_plain_counting(spark, data):
    texts = TEXTS + [r.text for r in spark.read.parquet(data("0.001") + "/documents.parquet").collect()]
    assert np.allclose(Q.statistics_of(texts), [plain(t) for t in texts], atol=1e-9)
    assert np.allclose(Q.statistics_of(TEXTS[::-1]), Q.statistics_of(TEXTS)[::-1]) and Q.statistics_of([]).shape == (0, len(STAT))


def test_long_texts_take_little_memory():
    """A text of any length is read whole, one beyond a hashing step too, without tables that grow with it."""
    text = "The word of line\nand " * 200_000 + "ünï 🙂 " * 3
    Q.statistics_of(["x"])
    tracemalloc.start()
    got = Q.statistics_of([text])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 50 * len(text), peak / len(text)
    short = text[-400_000:]
    assert np.allclose(Q.statistics_of([short]), [plain(short)], atol=1e-9) and got.shape == (1, len(STAT))


def test_query_equals_plain_loops(spark, data):
    """op7 as registered, against statistics, trees and threshold one document at a time."""
    d = data("0.001")
    docs = documents(spark, d)
    trees = Q.train(docs, labels(spark, d))
    want = {r.doc_id: walk(trees, plain(r.text)) for r in docs.collect() if r.text is not None}
    got = {r.doc_id: r.quality_score for r in queries()["op7_quality"](spark, d).collect()}
    assert got == {i: pytest.approx(s, abs=1e-9) for i, s in want.items() if s >= trees.threshold} and 0 < len(got) < len(want)


def test_each_text_is_judged_once(spark, data):
    plan = queries()["op7_quality"](spark, data("0.001"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("ArrowEvalPython") == 1


def test_thresholds():
    good, bad = np.arange(1000.0), np.arange(-100.0, 0.0)
    assert Q.threshold_for(good, bad) == -0.5
    noisy = np.concatenate([good, [-50.0]])
    assert (noisy >= Q.threshold_for(noisy, bad)).mean() >= 0.999 and (bad >= Q.threshold_for(noisy, bad)).mean() == 0
    assert (bad >= Q.threshold_for(np.concatenate([good, [-200.0] * 50]), bad)).mean() <= 0.05
    assert Q.threshold_for(good, bad[:0]) == 0.0


def test_training_with_clashing_columns_and_repeated_ids(spark, data):
    d = data("0.001")
    docs = documents(spark, d)
    odd = docs.unionByName(docs).withColumns({c: F.lit("x") for c in ("picked_id", "y", "h", "quality", "toxic", "log_chars")}).unionByName(docs.limit(3).withColumns({c: F.lit("x") for c in ("picked_id", "y", "h", "quality", "toxic", "log_chars")}).withColumn("text", F.lit(None).cast("string")))
    one, two = Q.train(docs, labels(spark, d)), Q.train(odd, labels(spark, d).withColumn("text", F.lit(1)))
    assert np.array_equal(one.feature, two.feature) and np.array_equal(one.leaf, two.leaf) and one.threshold == two.threshold


def test_all_labelled_documents_are_learnt_from(spark):
    """More than any sample: the trees equal those grown here from every document, and each is judged."""
    rng = np.random.default_rng(5)
    rows = [(i, " ".join(rng.choice(["word", "other", "Text,", "##", "7"], rng.integers(3, 30))), int(rng.random() < 0.5)) for i in range(7001)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, quality int")
    got = Q.train(df, df)
    assert got.held_out["documents"] == 7001
    known = Q.labelled_statistics(df, df).toPandas().sort_values(["h", "y"])
    x, y = known[STAT].to_numpy(), known["y"].to_numpy()
    assert sorted(map(tuple, x.tolist())) == sorted(map(tuple, Q.statistics_of([t for _, t, _ in rows]).tolist()))
    edges = [Q.quantile_edges(*np.unique(Q.slots(x[:, j]), return_counts=True)) for j in range(len(STAT))]
    want = Q.at_edges(Q.grow(Q.binned(x, edges), y), edges)
    assert np.array_equal(got.feature, want.feature) and np.array_equal(got.cut, want.cut) and np.allclose(got.leaf, want.leaf)


def test_slots_keep_the_order():
    x = np.sort(np.concatenate([np.random.default_rng(6).normal(size=500), [0.0, -0.0, 1.0, 1 / 3, -1e-17, 1e300]]))
    slot = Q.slots(x)
    assert (np.diff(slot) >= 0).all() and (x <= Q.slot_ends(slot)).all() and np.array_equal(Q.slots(Q.slot_ends(slot)), slot)
    assert (np.abs(Q.slot_ends(slot) - x) <= np.abs(x) / 4096 + 1e-300).all()


def test_held_out_accuracy(spark, data):
    docs = spark.read.parquet(data("0.1") + "/documents.parquet")
    got = Q.train(docs, spark.read.parquet(data("0.1") + "/labels.parquet")).held_out
    assert got["kept_good"] > 0.99 and got["dropped_bad"] > 0.95


def test_edges_of_input(spark, data):
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    trees = Q.train(docs, spark.read.parquet(data("0.01") + "/labels.parquet"))
    good = docs.where("doc_id = (SELECT 1)").first().text
    rows = [(1, None), (2, ""), (None, "word " * 400_000), (3, good), (3, good)]
    df = spark.createDataFrame(rows, DOCS).withColumn("quality_score", F.lit("x"))
    out = Q.quality_filter(df, trees)
    assert out.columns == df.columns and [r for r in out.collect() if r.text is None] == []
    assert sum(r.doc_id == 3 for r in out.collect()) in (0, 2)
    scored = {r.doc_id: r.s for r in Q.with_quality(df, trees, "s").collect()}
    assert scored[1] is None and scored[2] is not None
    assert Q.quality_filter(df.limit(0), trees).count() == 0


def test_labels_without_use(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, None)], DOCS)
    for rows in ([], [(1, None, 0)], [(1, 1, 0)], [(9, 1, 0)]):
        trees = Q.train(docs, spark.createDataFrame(rows, "doc_id bigint, quality int, toxic int"))
        assert Q.quality_filter(docs, trees).count() == 1
