"""Queries against their SQL where rows can't be scored, or texts are long."""

import random

import duckdb
import numpy as np
import pytest

from textredun.operators import metrics, spectrum, tuning
from textredun.plans import workloads


@pytest.fixture
def agree(spark, tmp_path):
    """Holds a query against its SQL over given documents (doc_id, text, lang) and labels (doc_id, quality)."""

    def check(name, docs, labels):
        spark.createDataFrame(docs, "doc_id bigint, text string, lang string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
        spark.createDataFrame(labels, "doc_id bigint, quality int").coalesce(1).write.parquet(f"{tmp_path}/labels.parquet")
        con = duckdb.connect()
        for t in ("documents", "labels"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
        got, want = workloads.queries()[name](spark, str(tmp_path)), con.execute(workloads.oracle_sql()[name])
        assert got.columns == [c[0] for c in want.description]
        rows = sorted(map(tuple, got.collect()), key=str)
        assert rows == sorted(want.fetchall(), key=str) and rows
        return rows

    return check


def test_labelled_texts_without_a_score(agree):
    """Texts too short to score are in no share of the curve."""
    docs = [(i, f"text number {i} with words {i * i} of its own " * (1 + i % 3), "en") for i in range(40)] + [(100 + i, "abc"[: i % 4], "en") for i in range(30)] + [(200, None, "en")]
    agree("threshold_curve", docs, [(d[0], int(d[0] % 5 > 0)) for d in docs])


def test_clean_texts_longer_than_a_group_of_scored_ones(agree):
    """More expected ranks than the texts of a group have."""
    rng = random.Random(0)
    words = ["".join(rng.choices("abcdefghijklmnop", k=9)) for _ in range(3000)]
    agree("zipf_empirical", [(1, " ".join(words), "en"), (2, " ".join(words[:500]), "en"), (3, "abcd", "en"), (4, "", "en"), *((i, "short text " * i, "de") for i in range(5, 300))], [(i, 1) for i in range(1, 300)])


def test_no_rank_is_left_out(spark):
    """A text of 270,000 different n-grams, and one that is scored by all of their ranks."""
    long = "".join(map(chr, range(0x20000, 0x20000 + 270_000)))
    docs = spark.createDataFrame([(1, long), (2, "aab" + long[:1000])], "doc_id bigint, text string")
    model = metrics.empirical_models(spectrum.spectra(docs, [("char", 1)]))[1].upto(300_000)
    want = np.zeros(len(model.q))
    want[:270_000] += 1 / 270_000 / 2
    want[:1002] += np.array([2, *[1] * 1001]) / 1003 / 2
    assert model.q == pytest.approx(want, rel=1e-12)
    assert model.q[:3] == pytest.approx(metrics.RankModel(shares=want[:270_000].tolist()).upto(10).q[:3])


def test_a_batch_holds_few_scores_of_a_large_grid(spark, monkeypatch):
    """However many settings there are; the session's own batch size comes back."""
    name, seen = "spark.sql.execution.arrow.maxRecordsPerBatch", []
    usual = spark.conf.get(name)
    monkeypatch.setattr(tuning, "written", lambda df, _: seen.append(int(spark.conf.get(name))) or spark.createDataFrame([], df.schema))
    docs, labels = spark.createDataFrame([(1, "a b", "en")], "doc_id bigint, text string, lang string"), spark.createDataFrame([(1, 1)], "doc_id bigint, quality int")
    settings = tuning.final_grid()
    tuning.grid_results(docs, labels, settings)
    assert 0 < seen[0] * len(settings) <= 1 << 21 and spark.conf.get(name) == usual
