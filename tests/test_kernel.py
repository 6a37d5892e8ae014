from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from textredun.operators import kernel
from textredun.operators import metrics as M
from textredun.operators import spectrum as S

TEXTS = ["abcabcabc", "", "aaaaaaaa", "abcde", "abcdefghijklmnopqrstuvwxyz", "é́🙂🙂x", "\r\n a\tb\n\n", " ", "a b a b a c", None]


def plain(text, unit, n):
    units = {"char": list, "token": str.split, "line": lambda t: t.split("\n")}[unit](text or "") if unit != "line" or text is not None else "".split("\n")
    counts = Counter(tuple(units[i : i + n]) for i in range(len(units) - n + 1))
    levels = Counter(counts.values())
    return sum(counts.values()), len(counts), sorted(levels.items(), reverse=True)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet="ab c\n🙂é", max_size=30), max_size=6), st.sampled_from(["char", "token", "line"]))
def test_kernel_equals_counting(texts, unit):
    codes, ends = kernel.units_of(texts, unit)
    for n, total, types, cut, c, v in kernel.spectra_of(codes, ends, [1, 2, 3, 5]):
        for i, t in enumerate(texts):
            assert (total[i], types[i], list(zip(c[cut[i] : cut[i + 1]].tolist(), v[cut[i] : cut[i + 1]].tolist()))) == plain(t, unit, n)


@pytest.mark.parametrize("strategy", ["arrow", "native", "relational"])
def test_strategies_agree(spark, strategy):
    df = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id bigint, text string")
    specs = [("char", 1), ("char", 3), ("char", 6), ("token", 1), ("token", 2), ("line", 1)]
    got = {(r.doc_id, r.unit, r.n): (r.n_total, r.n_types, [(e.c, e.v) for e in r.spectrum]) for r in S.spectra(df, specs, strategy).collect()}
    assert got == {(i, u, n): plain(t, u, n) for i, t in enumerate(TEXTS) for u, n in specs}


def test_regression_anchors(spark, data):
    sp = S.spectra(spark.read.parquet(data("0.01") + "/documents.parquet"), [("char", 6)], cap=S.BENCHMARK_CAP)
    rows = M.native_score(M.distinct_share(sp), M.Setting(norm="none")).where("n_total > 0").selectExpr("count(*)", "sum(distinct_share)", "sum(score)").first()
    assert rows[0] == 999 and rows[1] == pytest.approx(871.701571, abs=1e-6) and rows[2] == pytest.approx(3.899888, abs=1e-6)


def test_cap_and_histogram(spark):
    df = spark.createDataFrame([(1, "ab" * 4000), (2, "xyxyx")], "doc_id bigint, text string")
    assert {r.n_total for r in S.spectra(df, [("char", 2)], cap=5000).collect()} == {4999, 4}
    assert {r.n_total for r in S.spectra(df, [("char", 2)]).collect()} == {7999, 4}
    assert [tuple(r) for r in S.gram_histogram(df, n=2, top=1, cap=5000).orderBy("doc_id").collect()] == [(1, "ab", 2500, 1), (2, "xy", 2, 1)]
    assert {r.cnt for r in S.gram_histogram(df, n=2, top=1).collect()} == {4000, 2}
    with pytest.raises(ValueError):
        S.spectra(df, [("char", 0)])
    with pytest.raises(ValueError):
        S.spectra(df.drop("text"), [("char", 1)])


def test_window_ttr(spark):
    df = spark.createDataFrame([(1, "a b a a c d"), (2, "a"), (3, ""), (4, None)], "doc_id bigint, text string")
    got = {r.doc_id: (r.n_windows, r.score) for r in S.window_ttr(df, width=3, stride=2).collect()}
    assert got == {1: (3, pytest.approx((2 / 3 + 2 / 3 + 1) / 3)), 2: (1, 1.0), 3: (0, None), 4: (0, None)}


def test_no_exchange_and_narrow_read(spark, data):
    from textredun.functions.signature import Setting

    df = spark.read.parquet(data("0.01") + "/documents.parquet")
    for out in (M.score_documents(df, Setting()), M.score(S.spectra(df, [("char", 6)]), Setting()), M.native_score(S.spectra(df, [("char", 6)], "native"), Setting())):
        plan = out._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and "ReadSchema: struct<doc_id:bigint,text:string>" in plan


@pytest.mark.parametrize("n", [1, 2, 4])
def test_lines_count_like_their_document(spark, n):
    lines = [("a", i, t) for i, t in enumerate(["abc", "", "x", "", "", "abcabc"])] + [("b", 0, ""), ("c", 1, "xy"), ("c", 0, "🙂"), ("d", 0, None)]
    df = spark.createDataFrame(lines, "k string, i int, t string")
    texts = {"a": "abc\n\nx\n\n\nabcabc", "b": "", "c": "🙂\nxy"}
    got = {r.doc_id: (r.n_total, r.n_types, [(e.c, e.v) for e in r.spectrum]) for r in S.line_spectra(df, "k", ["i"], df.t, n).collect()}
    assert got == {k: plain(t, "char", n) for k, t in texts.items() if len(t) >= n}


def test_long_keys_give_way_to_ranks():
    rng = np.random.default_rng(0)
    texts = ["".join(map(chr, rng.integers(32, 3000, 4000))) * 2, "ab" * 3000, "".join(map(chr, rng.integers(32, 40, 500)))]
    for n, total, types, cut, c, v in kernel.spectra_of(*kernel.units_of(texts, "char"), [1, 7, 12, 40]):
        assert [(total[i], types[i], list(zip(c[cut[i] : cut[i + 1]].tolist(), v[cut[i] : cut[i + 1]].tolist()))) for i in range(3)] == [plain(t, "char", n) for t in texts]


def test_pooled_counts(spark):
    df = spark.createDataFrame([("x", "abab"), ("x", "ab"), ("y", "b"), ("y", None)], "g string, text string")
    counts = S.pooled_counts(df, "char", 2, "g")
    assert {(r.doc_id, r.gram, r.c) for r in counts.collect()} == {("x", "ab", 3), ("x", "ba", 1)}
    assert [(r.doc_id, r.n_total, r.n_types) for r in S.pooled_spectra(counts, "char", 2).collect()] == [("x", 4, 2)]
    assert [(r.gram, r["rank"]) for r in S.corpus_histogram(counts, 1).collect()] == [("ab", 1)]
