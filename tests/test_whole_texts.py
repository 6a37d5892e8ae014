from collections import Counter

import pytest

from textredun.functions.signature import Setting
from textredun.operators import tuning
from textredun.plans import workloads


@pytest.fixture(scope="module")
def place(spark, tmp_path_factory):
    """A long text that is clean for 20,000 characters and junk after it, one that is clean throughout, and a short one."""
    d = str(tmp_path_factory.mktemp("whole"))
    clean = "".join(f"{i * 7919 % 100003:05d} " for i in range(3400))
    rows = [(1, clean[:20_000] + "buy now! " * 8000, "en", "web", 1), (2, clean, "en", "web", 1), (3, "short text", "en", "web", 1)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{d}/documents.parquet")
    return d, {r[0]: r[1] for r in rows}


def moment(text):
    counts = Counter(text[i : i + 6] for i in range(len(text) - 5))
    n = sum(counts.values())
    return sum((c / n) ** 2 for c in counts.values()) * min(n, 2000)


@pytest.mark.parametrize("name", ["moment_sq_char6", "stream_scored", "sql_surface"])
def test_scores_read_texts_to_their_end(spark, place, name):
    got = {r.doc_id: r.score for r in workloads.queries()[name](spark, place[0]).collect()}
    assert got == {i: pytest.approx(moment(t), abs=1e-5) for i, t in place[1].items()}


def test_junk_behind_the_cap_is_found(spark, place):
    docs = spark.read.parquet(f"{place[0]}/documents.parquet")
    assert sorted(r.doc_id for r in tuning.filter_natural(docs, Setting(), 2.0).collect()) == [2, 3]
    profile = {r.doc_id: r.n_total for r in workloads.queries()["profile_char6"](spark, place[0]).collect()}
    assert profile == {i: len(t) - 5 for i, t in place[1].items()}


def test_moving_window_sees_every_word(spark, tmp_path):
    rows = [(1, " ".join(f"w{i}" for i in range(50)) + " tail" * 49), (2, " ".join(str(i * i % 37) for i in range(6000))), (3, "a b a"), (4, " "), (5, None)]
    spark.createDataFrame(rows, "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    want = {}
    for i, t in rows:
        u = (t or "").split()
        shares = [len(set(u[s : s + 50])) / len(u[s : s + 50]) for s in range(max(len(u) - 50, 0) + 1) if u]
        want[i] = (len(shares), pytest.approx(sum(shares) / len(shares), abs=1e-6) if shares else None)
    got = {r.doc_id: (r.n_windows, r.score) for r in workloads.queries()["window_ttr"](spark, str(tmp_path)).collect()}
    assert got == want and got[1][1] < 0.6


def test_nothing_is_cut_by_default(spark, data):
    """The price lists of sf0.1 hold 661,275 characters; all are read."""
    got = workloads.queries()["catalogue_docs_score"](spark, data("0.1")).collect()
    assert sum(r.n_total + 5 for r in got) == 661_275
    assert Setting().cap is None
