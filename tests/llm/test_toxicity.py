import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from textredun.llm import toxicity as T
from textredun.llm.common import documents, labelled_sample, labels
from textredun.llm.queries import queries

DOCS = "doc_id bigint, text string"


@pytest.fixture(scope="module")
def model():
    rng = np.random.default_rng(2)
    words = [f"w{i}" for i in range(300)]
    texts, y = [], []
    for i in range(400):
        sentences = [" ".join(rng.choice(words, 8)) for _ in range(rng.integers(1, 12))]
        if i % 4 == 0:
            at = rng.integers(len(sentences))
            sentences[at] += f" vile{rng.choice(['x', 'yz', 'er'])} rotten"
        texts.append(". ".join(sentences) + ".")
        y.append(int(i % 4 == 0))
    return T.fit(texts, y)


def test_document_score_is_the_noisy_or_of_its_sentences(model):
    text = "w1 w2. you rotten w3! w4\nvileness rotten. w5"
    score, spans = model.spans(text, model.memo())
    p = []
    for m in T.SENTENCE.finditer(text):
        feats = {f for w in T.WORD.findall(m.group().lower()) for f in T.word_features(w)}
        hit = [model.weights[f] for f in feats if f in model.weights]
        if hit:
            p.append(1 / (1 + math.exp(-(model.bias + sum(hit)))))
    assert score == pytest.approx(1 - math.prod(1 - x for x in p))
    assert [text[s:e].strip() for _, s, e, q in spans if q > 0.5] == ["you rotten w3!", "vileness rotten."]


def test_sentences_are_blamed_though_only_documents_are_labelled(spark, model):
    docs = spark.createDataFrame([(1, "w1 w2 w3. vilest rotten w4. w5 w6."), (2, "w1 w2. w3.")], DOCS)
    out = T.offending_sentences(docs, model).collect()
    assert [(r.doc_id, r.sentence_no, r.sentence.strip()) for r in out] == [(1, 1, "vilest rotten w4.")]
    assert docs.first().text[out[0].span_start : out[0].span_end] == out[0].sentence


def test_held_out_accuracy(spark, data):
    docs = spark.read.parquet(data("0.1") + "/documents.parquet")
    labels = spark.read.parquet(data("0.1") + "/labels.parquet")
    got = T.train(docs, labels, max_docs=2000).held_out
    assert got["documents"] > 200 and got["recall"] > 0.85 and got["false_alarms"] < 0.05


def test_edges_of_input(spark, model):
    long = "w1 w2. " * 30_000 + "rotten vilest."
    rows = [(1, None), (2, ""), (3, " \n."), (4, long), (None, "rotten vilest"), (5, "rotten vilest"), (5, "rotten vilest")]
    df = spark.createDataFrame(rows, DOCS).withColumn("toxicity", F.lit("x")).withColumn("sentence", F.lit(1))
    assert sorted((r.doc_id or 0) for r in T.offending_sentences(df, model).collect()) == [0, 4, 5, 5]
    kept = T.drop_toxic(df, model)
    assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect()) == [1, 2, 3]
    assert T.offending_sentences(df.limit(0), model).count() == 0 and T.drop_toxic(df.limit(0), model).count() == 0


def test_labels_without_use(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, None)], DOCS)
    for rows in ([], [(1, 1, None)], [(1, 1, 1)], [(9, 1, 1), (8, 1, 0)], [(2, 1, 1), (1, 1, 0)]):
        model = T.train(docs, spark.createDataFrame(rows, "doc_id bigint, quality int, toxic int"))
        assert T.offending_sentences(docs, model).count() == 0


def plain_rows(model, doc_id, text):
    """The query's rows of one document, word by word: noisy-or over the sentences with a known feature, then those to blame."""
    found, no = [], -1
    at = 0
    while at < len(text):
        if text[at] in ".!?\n":
            at += 1
            continue
        end = at
        while end < len(text) and text[end] not in ".!?\n":
            end += 1
        while end < len(text) and text[end] in ".!?":
            end += 1
        no += 1
        words, word = [], ""
        for c in text[at:end].lower() + " ":
            if c.isalnum() or c == "_":
                word += c
            elif word:
                words.append(word)
                word = ""
        z = {f: model.weights[f] for w in words for f in ["=" + w] + ["^" + w[:k] for k in (3, 4, 5, 6) if k < len(w)] if f in model.weights}
        if z:
            found.append((no, at, end, 1 / (1 + math.exp(-(model.bias + sum(z.values()))))))
        at = end
    score = 1 - math.prod(1 - p for *_, p in found)
    if score <= model.threshold:
        return []
    bar = min(model.threshold, max(p for *_, p in found) * (1 - 1e-12))
    return [(doc_id, no, a, b, text[a:b], score, p) for no, a, b, p in found if p > bar]


def test_query_equals_plain_loops(spark, data):
    """op3 as registered, over all documents."""
    d = data("0.01")
    docs = documents(spark, d)
    model = T.train(docs, labels(spark, d))
    want = sorted(x for r in docs.collect() if r.text is not None for x in plain_rows(model, r.doc_id, r.text))
    got = sorted((r.doc_id, r.sentence_no, r.span_start, r.span_end, r.sentence, r.doc_score, r.sentence_score) for r in queries()["op3_toxicity"](spark, d).collect())
    assert len(got) > 10 and [g[:5] for g in got] == [w[:5] for w in want]
    assert np.allclose([g[5:] for g in got], [w[5:] for w in want], atol=1e-12)


def test_gradient_of_the_noisy_or_likelihood():
    rng = np.random.default_rng(5)
    lengths = rng.integers(1, 5, 30)
    flat, starts = rng.integers(0, 12, lengths.sum()), np.concatenate([[0], np.cumsum(lengths)[:-1]])
    row, owner = np.repeat(np.arange(30), lengths), np.sort(rng.integers(0, 9, 30))
    y, weight, theta = rng.integers(0, 2, 9), rng.random(9) + 0.5, rng.normal(0, 0.7, 13)
    args = (flat, starts, row, owner, y, weight, 0.01)
    value, g = T.loss(theta, *args)
    clean = np.array([math.prod(1 - 1 / (1 + math.exp(-(theta[flat[row == s]].sum() + theta[-1]))) for s in np.flatnonzero(owner == d)) for d in range(9)])
    assert value == pytest.approx(-(weight * np.log(np.where(y == 1, np.maximum(1 - clean, 1e-12), clean))).sum() / 9 + 0.005 * (theta[:-1] ** 2).sum(), abs=1e-9)
    for i in range(13):
        step = np.zeros(13)
        step[i] = 1e-6
        assert g[i] == pytest.approx((T.loss(theta + step, *args)[0] - T.loss(theta - step, *args)[0]) / 2e-6, abs=1e-6)


def test_training_with_clashing_columns_and_repeated_ids(spark, data):
    d = data("0.001")
    docs = documents(spark, d)
    odd = docs.unionByName(docs.withColumn("text", F.concat("text", F.lit(" more")))).unionByName(docs.withColumn("text", F.lit(None).cast("string"))).withColumns({c: F.lit("x") for c in ("y", "h", "toxic", "picked_id")})
    one, two = T.train(docs, labels(spark, d)), T.train(odd, labels(spark, d))
    assert one.weights == two.weights and one.threshold == two.threshold


def test_labels_without_documents_take_no_place(spark):
    docs = spark.createDataFrame([(i, f"{'vile ' if i % 2 else ''}w{i}") for i in range(40)], DOCS)
    y = spark.createDataFrame([(i, 1, i % 2) for i in range(400)], "doc_id bigint, quality int, toxic int")
    assert len(labelled_sample(docs, y, "toxic", 15, "doc_id", "text").collect()) == 30
