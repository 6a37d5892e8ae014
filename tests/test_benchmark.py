import math

import pytest
from pyspark.sql import functions as F

from textredun.functions.signature import Setting, signature
from textredun.operators import corpus, measures, metrics, tasks, tuning

ROWS = "signature string, score double, is_natural boolean, weight double, valid boolean"


def test_worked_measures(spark):
    conf = spark.createDataFrame([(8.0, 2.0, 1.0, 9.0), (0.0, 0.0, 0.0, 0.0)], "tp double, fp double, fn double, tn double")
    a, b = measures.measures(conf).collect()
    assert a.f1 == pytest.approx(16 / 19) and a.p4 == pytest.approx(288 / 339) and a.precision == 0.8 and a.npv == 0.9
    assert a.p4 == pytest.approx(4 / (1 / a.precision + 1 / a.recall + 1 / a.specificity + 1 / a.npv))
    assert b.f1 is None and b.p4 is None
    assert measures.base_rate_purity(1e-5, 1.0, 0.01) == pytest.approx(0.000999, abs=1e-6)
    assert measures.base_rate_purity(1e-5, 1.0, 0.001) == pytest.approx(0.009901, abs=1e-6)
    assert measures.relative_gain(85, 78) == pytest.approx(0.0897, abs=1e-4)


def test_intervals(spark):
    df = spark.createDataFrame([(float(i), "a") for i in range(1, 11)] + [(3.0, "b")], "x double, k string")
    got = {r.k: (r.mean, r.ci95) for r in measures.mean_with_interval(df, "x", "k").collect()}
    assert got["a"] == (5.5, pytest.approx(2.165850, abs=1e-5)) and got["b"] == (3.0, None)
    mean, low, high = measures.bootstrap_interval([1, 2, 3, 4, 5])
    assert low < mean == 3 < high and measures.t_975(12) == pytest.approx(2.1788, abs=2e-3)


def brute(rows, objective):
    """Every score as threshold; the lowest of the best."""
    best = None
    for t in sorted({r[1] for r in rows}):
        tp = sum(r[3] for r in rows if r[2] and r[1] <= t)
        fp = sum(r[3] for r in rows if not r[2] and r[1] <= t)
        fn, tn = sum(r[3] for r in rows if r[2]) - tp, sum(r[3] for r in rows if not r[2]) - fp
        top, bottom = (2 * tp, 2 * tp + fp + fn) if objective == "f1" else (4 * tp * tn, 4 * tp * tn + (tp + tn) * (fp + fn))
        v = round(top / bottom, 12) if bottom else -1
        if best is None or v > best[1]:
            best = (t, v)
    return best


@pytest.mark.parametrize("objective", ["f1", "p4"])
def test_thresholds_equal_a_scan(spark, objective):
    import random

    rng = random.Random(4)
    rows = [("s", rng.randint(0, 15) / 4 + (0 if good else 1), good, 1.0 if good else 0.5, True) for good in [rng.random() < 0.6 for _ in range(200)]]
    got = tuning.tune_threshold(spark.createDataFrame(rows, ROWS), objective).first()
    assert (got.threshold, got.value) == pytest.approx(brute(rows, objective))


def test_thresholds_at_the_edges(spark):
    tie = [("s", 1.0, True, 1.0, True), ("s", 1.0, False, 1.0, True), ("s", 2.0, False, 1.0, True), ("s", 0.0, True, 1.0, False)]
    one = [("t", 1.0, True, 1.0, True), ("t", 3.0, True, 1.0, True)]
    none = [("u", 1.0, False, 0.0, True)]
    got = {r.signature: (r.threshold, r.value) for r in tuning.tune_threshold(spark.createDataFrame(tie + one + none, ROWS)).collect()}
    assert got["s"] == (1.0, pytest.approx(2 / 3)) and got["t"] == (3.0, 1.0) and got["u"] == (1.0, None)


def test_classes_and_halves(spark, data):
    c = tasks.classified(spark.read.parquet(data("0.01") + "/documents.parquet"), spark.read.parquet(data("0.01") + "/labels.parquet")).cache()
    assert {r.label_class: r["count"] for r in c.groupBy("label_class").count().collect()} == {"unsure": 601, "natural": 341, "noise": 51, "repetitive": 7}
    assert c.groupBy(F.md5("text")).agg(F.countDistinct("half").alias("n")).where("n > 1").count() == 0
    assert tasks.per_language_sample(c).groupBy("lang").count().where("count > 6").count() == 0
    sums = tasks.task(c, "noise", natural_share=0.75).groupBy("half", "is_natural").agg(F.sum("weight").alias("w")).collect()
    assert all(r.w == pytest.approx(0.75 if r.is_natural else 0.25) for r in sums)


def test_filter_and_partition(spark):
    docs = spark.createDataFrame([(1, "ab" * 500), (2, "the quick brown fox"), (3, "x"), (4, None)], "doc_id bigint, text string")
    assert sorted(r.doc_id for r in tuning.filter_natural(docs, Setting(), 2.0).collect()) == [2, 3, 4]
    assert sorted(r.doc_id for r in tuning.filter_natural(docs, Setting(), 2.0, keep_invalid=False).collect()) == [2]
    assert {r.doc_id: r.is_natural for r in tuning.partition_by_verdict(docs, Setting(), 2.0).collect()} == {1: False, 2: True, 3: None, 4: None}


def test_verdicts_are_of_rows_not_of_ids(spark):
    """Rows that share an id, or have none, are judged each by its own text; no row is lost or doubled; other columns pass."""
    rows = [(1, "ab" * 500, 7), (1, "the quick brown fox", 8), (None, "ab" * 500, 9), (None, "", 10), (None, "so it goes, now and then", 11)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, threshold int")
    line = spark.createDataFrame([(2.0,)], "threshold double")
    for t in (2.0, line):
        assert sorted(map(tuple, tuning.filter_natural(docs, Setting(), t).collect()), key=str) == sorted([rows[1], rows[3], rows[4]], key=str)
        got = tuning.partition_by_verdict(docs, Setting(), t)
        assert got.columns == ["doc_id", "text", "threshold", "score", "is_natural"] and sorted((r.threshold, r.is_natural) for r in got.collect() if r.is_natural is not None) == [(7, False), (8, True), (9, False), (11, True)]
    assert tuning.filter_natural(docs.limit(0), Setting(), 2.0).count() == 0
    with pytest.raises(ValueError):
        metrics.with_scores(docs, {"Threshold": Setting()})


def test_verdicts_move_no_text(spark, data):
    d = data("0.01")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    line = spark.createDataFrame([(2.0,)], "threshold double")
    for out in (tuning.filter_natural(docs, Setting(), line), tuning.partition_by_verdict(docs, Setting(), 2.0)):
        plan = out._jdf.queryExecution().executedPlan().toString()
        assert plan.count("ArrowEvalPython") == 1 and "Exchange hashpartitioning" not in plan and "SortMergeJoin" not in plan


def test_thresholds_as_of_a_time(spark):
    scored = spark.createDataFrame([(i, "s", 1.0, at) for i, at in enumerate([1, 5, 6, 9])] + [(9, "t", 1.0, 9)], "doc_id bigint, signature string, score double, at int")
    versions = spark.createDataFrame([("s", 0.5, 5), ("s", 0.7, 8)], "signature string, threshold double, at int")
    assert {r.doc_id: r.threshold for r in tuning.threshold_as_of(scored, versions).collect()} == {0: None, 1: 0.5, 2: 0.5, 3: 0.7, 9: None}


def test_corpus_report_adds_up(spark):
    rows = spark.createDataFrame([("clean", "high", "en", 1.0), ("clean", "high", "en", 3.0), ("clean", "low", "fr", 5.0), ("noisy", "low", "fr", None)], "split string, tier string, lang string, x double")
    got = {(r.split, r.tier): (r.n_docs, r.micro_x, r.macro_x) for r in corpus.corpus_report(rows, ["x"]).collect()}
    assert got["clean", None] == (3, 3.0, 3.5) and got["noisy", "low"] == (1, None, None) and got[None, None][:2] == (4, 3.0)


def test_grids_hold_what_did_best():
    for grid in (tuning.final_grid(), tuning.deep_grid()):
        names = [signature(s) for s in grid]
        assert len(names) == len(set(names))
        grid = [s for s in grid if isinstance(s, Setting)]
        assert {s.k for s in grid if s.g == "pow" and s.metric == "moment"} >= {1.5, 2.0, 3.0} and any(s.g == "sq_entropy" for s in grid) and {"sq", "log"} <= {s.d for s in grid}
        assert {2000.0, math.inf} <= {s.asymptote for s in grid} and {4, 5, 6} <= {s.n for s in grid}


def test_tiers_are_there_at_any_size(spark):
    rows = spark.createDataFrame([("en", "clean")] * 5 + [("fr", "clean"), ("fr", "noisy"), ("de", "clean")], "lang string, split string").withColumn("x", F.lit(1.0))
    assert {r.lang: r.tier for r in corpus.by_language(rows, ["x"]).collect()} == {"en": "high", "fr": "low", "de": "low"}


@pytest.fixture(scope="module")
def searched(spark, data):
    lengths, kinds = (1, 4, 5, 6, 7), ({"k": 2.0},)
    grid = [Setting(metric="ttr", n=n) for n in lengths] + [Setting(n=n, asymptote=a, **k) for n in lengths for a in (500.0, 2000.0) for k in kinds] + [Setting(metric="zipf", n=n) for n in lengths]
    d = data("0.1")
    return tuning.grid_results(spark.read.parquet(d + "/documents.parquet"), spark.read.parquet(d + "/labels.parquet"), grid).cache()


def test_long_ngrams_win_for_repetition(searched):
    best = {(r.metric, r.n): r.test_f1 for r in tuning.best_setting_per_n(searched).where("tuned_on = 'repeat'").collect()}
    for m in ("ttr", "moment"):
        assert min(best[m, n] for n in (5, 6, 7)) > best[m, 1] + 0.1
    assert max((4, 5), key=lambda n: best["zipf", n]) in (4, 5) and max(best["zipf", n] for n in (4, 5)) > best["zipf", 1]


def test_repetition_is_easier_than_noise(searched):
    m = {(r.metric, r.tuned_on, r.tested_on): r.mean for r in tuning.tune_test_matrix(searched, 3).collect()}
    assert all(m[x, "repeat", "repeat"] > m[x, "noise", "noise"] for x in ("ttr", "moment", "zipf"))
    assert m["moment", "noise", "noise"] > m["ttr", "noise", "noise"] - 0.02
    effect = tuning.parameter_effect(searched).where("parameter = 'n' AND metric = 'moment' AND tuned_on = 'repeat'").collect()
    assert {r.value for r in effect} == {"1", "4", "5", "6", "7"}
    assert tuning.generalisation_gap(searched, 3).count() == 6
