"""Every query that SQL can express, against DuckDB, on the smallest tables."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry
from textredun.plans import workloads

SQL = entry.oracle_sql()
D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{D}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def cells(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    show = lambda x: "-" if x is None else f"{x:.6f}" if isinstance(x, float) else str(x)
    return sorted(tuple(show(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, duck, name):
    df = entry.queries()[name](spark, D)
    got = duck.execute(SQL[name])
    columns = [c[0] for c in got.description]
    assert sorted(columns) == sorted(df.columns)
    assert cells(df.collect(), df.columns) == cells(got.fetchall(), columns)


def test_the_rest_run_by_rows(spark):
    for name in sorted(set(workloads.queries()) - set(SQL)):
        assert workloads.queries()[name](spark, D).count() > 0, name


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() == 200


def test_sketches_are_close(spark, duck):
    """The two approximate queries against exact numbers."""
    exact = dict(duck.execute("SELECT lang, count(DISTINCT g) FROM (SELECT lang, substr(text, i, 3) AS g FROM documents, unnest(range(1, length(text)::BIGINT - 1)) AS u(i)) GROUP BY lang").fetchall())
    got = {r.lang: r.n_types for r in workloads.queries()["vocabulary_size"](spark, D).collect()}
    assert got.keys() == exact.keys() and all(abs(got[k] / exact[k] - 1) < 0.1 for k in got)
    rows = {r.signature: r for r in workloads.queries()["score_quantiles"](spark, D).collect()}
    scores = sorted(r.score for r in workloads.queries()["moment_sq_char6"](spark, D).collect() if r.score is not None)
    assert rows[workloads.signature(workloads.MOMENT6)].p50 == pytest.approx(scores[(len(scores) - 1) // 2], abs=1e-3)


def test_run_cost(spark):
    r = workloads.queries()["run_cost"](spark, D).first()
    assert r.n_docs == 200 and r.n_chars == spark.read.parquet(f"{D}/documents.parquet").selectExpr("sum(length(text))").first()[0] and r.seconds > 0 and r.spectrum_bytes_per_doc > 16
