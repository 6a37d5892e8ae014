from pyspark.sql import functions as F

from textredun.llm.exact_dedup import exact_dedup

DOCS = "doc_id bigint, text string"


def test_smallest_id_of_equal_bytes_stays(spark):
    long = "x" * 300_000
    rows = [(5, "a b"), (3, "a b"), (9, " a b\n"), (4, "a  b"), (6, "A b"), (7, long), (8, long), (2, long + "y"), (1, "a\r\nb"), (10, "a\nb"), (11, "a\rb")]
    got = {r.doc_id: r.text for r in exact_dedup(spark.createDataFrame(rows, DOCS)).collect()}
    assert got == {3: "a b", 4: "a  b", 6: "A b", 7: long, 2: long + "y", 1: "a\r\nb"}


def test_nulls_empties_repeats_and_names(spark):
    rows = [(1, None), (1, None), (2, ""), (3, " \t"), (None, "t"), (4, "t"), (4, "t"), (None, "only"), (None, None)]
    df = spark.createDataFrame(rows, DOCS)
    for name in ("norm", "digest", "prefix", "changed", "before", "Doc"):
        df = df.withColumn(name, F.lit(name))
    out = exact_dedup(df)
    assert out.columns == df.columns
    assert sorted((r.doc_id or 0, r.text or "-") for r in out.collect()) == [(0, "-"), (0, "only"), (1, "-"), (1, "-"), (2, "-"), (4, "t")]
    assert all(r.norm == "norm" and r.before == "before" for r in out.collect())
    assert exact_dedup(df.limit(0)).count() == 0


def test_shared_prefixes_split_and_stay_exact(spark):
    rows = [(i, "the same beginning of very many documents " + str(i % 700)) for i in range(2000)]
    got = exact_dedup(spark.createDataFrame(rows, DOCS).repartition(7))
    assert sorted(r.doc_id for r in got.collect()) == list(range(700))


def test_one_shuffle_and_no_python(spark):
    plan = exact_dedup(spark.createDataFrame([(1, "a")], DOCS))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "rangepartitioning" in plan and "Python" not in plan and "Arrow" not in plan
