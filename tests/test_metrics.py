import math
from dataclasses import replace

import numpy as np
import pytest

from textredun.functions.signature import Setting, parse_signature, signature
from textredun.operators import metrics as M
from textredun.operators import spectrum as S

RAW = Setting(n=3, norm="none")
ZIPF = Setting(metric="zipf", n=3, norm="none")


def of(text, s, model=None):
    from textredun.operators import kernel

    codes, ends = kernel.units_of([text], s.unit)
    ((n, total, types, cut, c, v),) = kernel.spectra_of(codes, ends, [s.n])
    return float(M.score_spectra(c, v, cut, total, types, s, model)[0])


@pytest.mark.parametrize(
    "setting, value",
    [
        (Setting(metric="ttr", n=3), 0.571429),
        (RAW, 0.346939),
        (RAW.but(lam=1), 0.34),
        (RAW.but(eps=2), 1.0),
        (RAW.but(norm="ratio"), 2.428571),
        (RAW.but(norm="ratio", asymptote=4), 1.387755),
        (RAW.but(k=1.5), 0.586007),
        (RAW.but(k=3), 0.125364),
        (RAW.but(g="entropy"), 1.078992),
        (RAW.but(g="sq_entropy"), 0.388093),
        (ZIPF, 0.024625),
        (ZIPF.but(d="log"), -8.754750),
        (ZIPF.but(d="sq_log"), 28.603799),
        (ZIPF.but(d="jsd"), 0.009411),
        (ZIPF.but(d="abs"), 0.233766),
        (ZIPF.but(d="kl_pq"), 0.039075),
        (ZIPF.but(d="kl_qp"), 0.036677),
        (ZIPF.but(norm="ratio"), 0.300245),
    ],
)
def test_worked_example(setting, value):
    assert of("abcabcabc", setting) == pytest.approx(value, abs=1e-6)


def test_tokens():
    s = Setting(unit="token", n=2, norm="none")
    assert of("a b a b a c", s) == pytest.approx(0.36) and of("a b a b a c", s.but(metric="ttr")) == pytest.approx(0.4)


ALL_MOMENTS = [RAW.but(norm="ratio", **x) for x in ({"k": 1.5}, {"k": 2.0}, {"k": 3.0}, {"g": "sq_entropy"})]


@pytest.mark.parametrize("s", ALL_MOMENTS)
def test_without_repetition_the_ratio_is_one(s):
    assert of("abcdefghijklmnopqrstuvwxyz", s) == pytest.approx(1)
    assert of("abcdefghijklmnopqrstuvwxyz", Setting(metric="ttr", n=3)) == 0
    assert of("aaaaaaaaa", RAW) == 1


def test_invariants():
    text = "the cat sat on the mat and the cat sat on the hat"
    other = text.translate(str.maketrans("abcdehmnost ", "XYZWVUTSRQP-"))
    for s in (*ALL_MOMENTS, ZIPF, ZIPF.but(d="jsd"), ZIPF.but(d="log")):
        assert of(text, s) == pytest.approx(of(other, s))
    assert of(text, RAW.but(lam=1e9)) == pytest.approx(1 / len({text[i : i + 3] for i in range(len(text) - 2)}), rel=1e-6)
    assert 0 <= of(text, ZIPF.but(d="jsd")) <= math.log(2)
    assert of(text, RAW.but(norm="ratio", asymptote=math.inf)) == of(text, RAW.but(norm="ratio", asymptote=10**9))
    for top in (1, 3, 10**6):
        v, p = M.shares(np.array([3.0, 2.0, 1.0]), np.array([1.0, 2.0, 4.0]), np.zeros(3, int), np.array([11.0]), RAW.but(top_k=top, lam=0.5))
        assert (v * p).sum() == pytest.approx(1) and v.sum() == min(top, 7)


@pytest.mark.parametrize("support", ["observed", "bounded"])
def test_prefix_sums_equal_ranks(support):
    text = "the cat sat on the mat and the cat sat on the hat " * 3
    s = ZIPF.but(support=support, shift=2.7, exponent=1.1)
    counts = sorted((text[i : i + 3] for i in range(len(text) - 2)))
    c = np.array(sorted((counts.count(g) for g in set(counts)), reverse=True), dtype=float)
    size = len(c) if support == "observed" else max(len(c), len(counts))
    q = (np.arange(1, size + 1) + 2.7) ** -1.1
    p = np.concatenate([c / c.sum(), np.zeros(size - len(c))])
    assert of(text, s) == pytest.approx(((q / q.sum() - p) ** 2).sum(), abs=1e-12)
    assert of(text, s.but(d="abs")) == pytest.approx(np.abs(q / q.sum() - p).sum(), abs=1e-12)


def test_array_form_equals_kernel(spark, data):
    sp = S.spectra(spark.read.parquet(data("0.001") + "/documents.parquet"), [("char", 3)]).cache()
    for s in (*ALL_MOMENTS, Setting(metric="ttr", n=3), RAW.but(lam=0.1, eps=1, top_k=7), RAW.but(norm="difference"), RAW.but(g="entropy", norm="ratio"), RAW.but(norm="ratio", mode="hyperbolic"), RAW.but(norm="ratio", mode="exponential"), RAW.but(eps=0.002, eps_on="prob")):
        a = {r.doc_id: r.score for r in M.native_score(sp, s).collect()}
        b = {r.doc_id: r.score for r in M.score(sp, s).collect()}
        assert a.keys() == b.keys() and all((a[i] is None) == (b[i] is None) and (a[i] is None or a[i] == pytest.approx(b[i], rel=1e-9, abs=1e-12)) for i in a), signature(s)


def test_short_and_null_texts_are_not_valid(spark):
    df = spark.createDataFrame([(1, None), (2, ""), (3, "abcde"), (4, "abcdef")], "doc_id bigint, text string")
    got = {r.doc_id: (r.score, r.valid) for r in M.score(S.spectra(df, [("char", 6)]), Setting()).collect()}
    assert got == {1: (None, False), 2: (None, False), 3: (None, False), 4: (1.0, True)}


def test_ensembles(spark):
    df = spark.createDataFrame([(1, "a b a b a b"), (2, "abcdef ghi jkl")], "doc_id bigint, text string")
    settings = [Setting(n=3), Setting(unit="token", n=1)]
    scored = M.score(S.spectra(df, [s.spec for s in settings]), settings).cache()
    one = {r.doc_id: r.score for r in scored.where(scored.signature == signature(settings[0])).collect()}
    assert {r.doc_id: r.score for r in M.ensemble(scored.where(scored.signature == signature(settings[0]))).collect()} == one
    both = {r.doc_id: r.score for r in M.ensemble(scored).collect()}
    assert both[1] == pytest.approx(np.mean([r.score for r in scored.collect() if r.doc_id == 1]))
    z = {r.doc_id: r.score for r in M.ensemble(scored, "standardised", M.score_stats(scored)).collect()}
    assert z[1] + z[2] == pytest.approx(0) and z[1] > 0


def test_rank_models(spark):
    df = spark.createDataFrame([(1, "aab"), (2, "aaaabbc")], "doc_id bigint, text string")
    sp = S.spectra(df, [("char", 1)])
    got = {r["rank"]: r.share for r in M.mean_rank_shares(sp).collect()}
    assert got == pytest.approx({1: (2 / 3 + 4 / 7) / 2, 2: (1 / 3 + 2 / 7) / 2, 3: 1 / 14})
    model = M.empirical_models(sp)[1]
    assert M.score(sp, Setting(metric="zipf", n=1, norm="none"), {1: model}).count() == 2
    fit = M.fit_rank_model(sp).first()
    slope, intercept = np.polyfit(np.log([1, 2, 3]), np.log([got[1], got[2], got[3]]), 1)
    assert fit.exponent == pytest.approx(-slope) and fit.intercept == pytest.approx(intercept) and 0 < fit.r2 <= 1


@pytest.mark.parametrize(
    "s",
    [Setting(), Setting(metric="ttr", cap=None), Setting(metric="zipf", d="sq_log", exponent=1.07, shift=2.7, support="bounded"), Setting(g="sq_entropy", asymptote=math.inf), Setting(lam=0.1, eps=0.5, eps_on="prob", top_k=100, k=1.5, mode="hyperbolic", norm="difference"), Setting(unit="token", n=2, norm="none")],
)
def test_signatures_come_back(s):
    back = parse_signature(signature(s))
    assert signature(back) == signature(s) and (s.metric == "ttr" or back == replace(s, **({} if s.g == "pow" else {"k": back.k}) | ({} if s.metric == "moment" else {"g": back.g, "k": back.k}) | ({"d": back.d} if s.metric == "moment" else {})))


@pytest.mark.parametrize("bad", ["moment|u=char", "moment|x=1", "nonsense|u=char|n=1", signature(Setting()) + "|v=1", signature(Setting()).replace("v=1", "v=9")])
def test_bad_signatures(bad):
    with pytest.raises(ValueError):
        parse_signature(bad)
