import pytest
from pyspark.sql import functions as F

from textredun.functions import sql
from textredun.functions.signature import Setting, signature
from textredun.operators import metrics
from textredun.operators import spectrum as sp
from textredun.sources import documents as src
from textredun.sources import sinks
from textredun.streaming import scoring


@pytest.mark.parametrize("format", ["parquet", "orc", "json", "csv"])
def test_formats_come_back(spark, tmp_path, format):
    df = spark.createDataFrame([(1, 'a "b"\nc', "x"), (2, "ü", "y")], "n bigint, body string, lang string")
    df.write.format(format).options(**({"header": True, "escape": '"'} if format == "csv" else {})).save(f"{tmp_path}/d")
    got = src.read_documents(spark, f"{tmp_path}/d", format, "n", "body", "n bigint, body string, lang string" if format == "csv" else None)
    assert sorted((r.doc_id, r.text) for r in got.collect()) == [(1, 'a "b"\nc'), (2, "ü")]
    with pytest.raises(ValueError):
        src.read_documents(spark, f"{tmp_path}/d", format, "none", "body")


def test_text_files(spark, tmp_path):
    (tmp_path / "a.txt").write_text("one\ntwo\n")
    assert {r.text for r in src.read_documents(spark, str(tmp_path), "text").collect()} == {"one", "two"}
    assert [r.text for r in src.read_documents(spark, str(tmp_path), "wholetext").collect()] == ["one\ntwo\n"]
    with pytest.raises(ValueError):
        src.read_documents(spark, str(tmp_path), "xls")


def test_derived_documents(spark):
    turns = spark.createDataFrame([(1, 2, "user", "c"), (1, 1, "assistant", "b"), (1, 0, "user", "a"), (2, 0, "user", None)], "conv_id bigint, turn bigint, role string, text string")
    assert {r.doc_id: r.text for r in src.conversation_docs(turns).collect()} == {1: "a\nb\nc", 2: ""}
    assert {r.doc_id: r.text for r in src.conversation_docs(turns, "assistant").collect()} == {1: "b"}
    page = spark.createDataFrame([(1, "u", "<nav>x</nav><script>var a='<p>';</script><article id=1><p>Hello\n <b>you</b></p></article>")], "page_id bigint, url string, html string")
    assert {r.variant: r.text for r in src.page_docs(page).collect()} | {"html": ""} == {"html": "", "stripped": "x Hello you", "article": "Hello you"}


def test_markup_raises_the_score(spark, data):
    docs = src.page_docs(spark.read.parquet(data("0.01") + "/pages.parquet"))
    s = metrics.score(sp.spectra(docs.select(F.concat_ws(":", "doc_id", "variant").alias("doc_id"), "text"), [("char", 6)]), Setting())
    mid = {r.v: r.m for r in s.where("valid").groupBy(F.split("doc_id", ":")[1].alias("v")).agg(F.median("score").alias("m")).collect()}
    assert mid["html"] > mid["stripped"] > 1


def test_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, True), (2, False)], "doc_id bigint, is_natural boolean")
    sinks.write_scored(df, f"{tmp_path}/o", partition_by=("is_natural",))
    assert spark.read.parquet(f"{tmp_path}/o/is_natural=true").count() == 1
    with pytest.raises(Exception):
        sinks.write_scored(df, f"{tmp_path}/o")


def test_stream_equals_batch(spark, tmp_path, data):
    docs = spark.read.parquet(data("0.001") + "/documents.parquet")
    docs.repartition(4).write.parquet(f"{tmp_path}/in")
    out = scoring.run_to_files(scoring.scored_stream(scoring.read_stream(spark, f"{tmp_path}/in", 1), Setting()), f"{tmp_path}/s")
    want = metrics.score(sp.spectra(docs, [("char", 6)]), Setting())
    assert sorted(map(str, out.collect())) == sorted(map(str, want.collect()))


def test_micro_batches_replace_themselves(spark, tmp_path):
    write = sinks.batch_sink(f"{tmp_path}/b")
    for _ in range(2):
        write(spark.range(3), 7)
    assert spark.read.parquet(f"{tmp_path}/b").count() == 3


def test_late_events_are_dropped(spark, tmp_path):
    rows = lambda *x: spark.createDataFrame([(u, t, at) for u, t, at in x], "user_id bigint, event_type string, at string").select("user_id", "event_type", F.col("at").cast("timestamp_ntz").alias("ts"))
    for i, part in enumerate([rows((1, "a", "2024-01-01 00:10:00"), (1, "a", "2024-01-01 00:20:00"), (1, "b", "2024-01-01 05:00:00")), rows((1, "z", "2024-01-01 00:30:00")), rows((1, "c", "2024-01-01 09:00:00"))]):
        part.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = spark.readStream.schema("user_id bigint, event_type string, ts timestamp_ntz").parquet(f"{tmp_path}/in")
        out = scoring.run_to_files(scoring.event_windows(stream), f"{tmp_path}/w")
    got = [(r.n_events, r.n_types, r.moment) for r in out.orderBy("window_start").collect()]
    assert got == [(2, 1, 1.0), (1, 1, 1.0)]


def test_sql_functions(spark):
    sql.register(spark)
    spark.createDataFrame([(1, "abcabcabc"), (2, None), (3, "ab")], "doc_id bigint, text string").createOrReplaceTempView("few")
    name = signature(Setting(n=3, norm="none"))
    got = {r.doc_id: r.s for r in spark.sql(f"SELECT doc_id, redundancy(text, '{name}') AS s FROM few").collect()}
    assert got == {1: pytest.approx(17 / 49), 2: None, 3: None}
    grams = spark.sql("SELECT doc_id, gram, position FROM few, LATERAL ngrams(text, 'char', 3)").collect()
    assert len(grams) == 7 and grams[0].gram == "abc"
    assert {(r.c, r.v) for r in spark.sql("SELECT c, v FROM few, LATERAL spectrum(text, 'char', 3)").collect()} == {(3, 1), (2, 2)}


def test_state_by_user_survives_batches(spark, tmp_path, data):
    """Counts kept by user over several batches, and over a restart, are those of all events at once."""
    events = spark.read.parquet(data("0.001") + "/events.parquet").select("user_id", "event_type", "ts", "value")
    want = {r.user_id: (r.n_events, r.n_types, pytest.approx(r.moment)) for r in scoring.type_moment(events.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_events"), F.sort_array(F.collect_list("event_type")).alias("types"))).collect()}
    half = events.where("value < 50"), events.where("NOT value < 50 OR value IS NULL")
    for part in half:
        part.repartition(3).write.mode("append").parquet(f"{tmp_path}/in")
        stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
        got = scoring.run_updates(scoring.user_moments(stream), f"{tmp_path}/u", ["user_id"])
    assert {r.user_id: (r.n_events, r.n_types, r.moment) for r in got.collect()} == want
    windows = scoring.run_updates(scoring.event_windows(spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in"), late="3650 days"), f"{tmp_path}/w", ["window_start", "user_id"])
    assert sorted(map(str, windows.collect())) == sorted(map(str, scoring.event_windows(events).collect()))


def test_first_of_each_content(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a", "2024-01-01 00:00:00"), (1, "a", "2024-01-01 00:01:00"), (2, "a", "2024-01-01 00:02:00")], "user_id int, event_type string, at string").withColumn("at", F.col("at").cast("timestamp"))
    rows.write.parquet(f"{tmp_path}/in")
    once = scoring.first_of_each(spark.readStream.schema(rows.schema).parquet(f"{tmp_path}/in"), ["user_id", "event_type"], "at", "1 day")
    assert sorted((r.user_id, r.event_type) for r in scoring.run_to_files(once, f"{tmp_path}/o").collect()) == [(1, "a"), (2, "a")]
