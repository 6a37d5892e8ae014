"""Documents scored as they arrive, and redundancy of event sequences per window."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from textredun.functions.signature import Setting
from textredun.operators import metrics
from textredun.sources.sinks import batch_sink


def read_stream(spark: SparkSession, path: str, files_per_batch: int = 8, schema: str = "doc_id bigint, text string, lang string, source string, n_chars bigint", glob: str | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    return (reader.option("pathGlobFilter", glob) if glob else reader).parquet(path)


def scored_stream(docs: DataFrame, s: Setting) -> DataFrame:
    """The batch plan, unchanged: no state, append mode."""
    return metrics.score_documents(docs, s)


def type_moment(counts: DataFrame) -> DataFrame:
    """``n_events`` and sorted ``types`` become events, distinct types and the moment x**2 of their shares."""
    kinds = F.array_distinct("types")
    share = lambda k: F.size(F.filter("types", lambda x: x == k)) / F.col("n_events")
    second = F.aggregate(kinds, F.lit(0.0), lambda a, k: a + share(k) * share(k))
    return counts.withColumns({"n_types": F.size(kinds).cast("bigint"), "moment": second}).drop("types")


def _timed(events: DataFrame, late: str) -> DataFrame:
    return events.select("user_id", "event_type", F.col("ts").cast("timestamp").alias("at")).withWatermark("at", late)


def event_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Per user and session (events less than ``gap`` apart): events, distinct types and the moment of their shares."""
    counts = _timed(events, late).groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n_events"), F.sort_array(F.collect_list("event_type")).alias("types"))
    return type_moment(counts.select(F.col("w.start").alias("session_start"), "user_id", "n_events", "types"))


def first_of_each(rows: DataFrame, keys: list[str], time: str, within: str) -> DataFrame:
    """The first row of each key; keys are forgotten ``within`` behind the newest row."""
    return rows.withWatermark(time, within).dropDuplicatesWithinWatermark(keys)


def user_moments(events: DataFrame) -> DataFrame:
    """Per user, after each batch that has events of theirs: events so far, distinct types and the moment x**2 of their shares.

    The state is one count for each user and type, however many events there were.
    """

    def step(key, parts, state):
        counts = dict(zip(*state.get)) if state.exists else {}
        for part in parts:
            for kind, n in part["event_type"].value_counts(dropna=False).items():
                kind = None if kind != kind else kind
                counts[kind] = counts.get(kind, 0) + int(n)
        state.update((list(counts), list(counts.values())))
        n = sum(counts.values())
        yield pd.DataFrame({"user_id": [key[0]], "n_events": [n], "n_types": [len(counts)], "moment": [sum((c / n) ** 2 for c in counts.values())]})

    rows = events.select("user_id", "event_type")
    kind = events.schema["user_id"].dataType.simpleString()
    return rows.groupBy("user_id").applyInPandasWithState(step, f"user_id {kind}, n_events bigint, n_types bigint, moment double", "types array<string>, counts array<bigint>", "update", "NoTimeout")


def event_windows(events: DataFrame, width: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Per user and window: events, distinct event types, and the moment x**2 of their shares.

    Works on batches and streams; on a stream, windows close ``late`` behind the newest
    event, and what comes later is dropped.
    """
    counts = _timed(events, late).groupBy(F.window("at", width).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n_events"), F.sort_array(F.collect_list("event_type")).alias("types"))
    return type_moment(counts.select(F.col("w.start").alias("window_start"), "user_id", "n_events", "types"))


def run_to_files(stream: DataFrame, folder: str) -> DataFrame:
    """All that has arrived so far, through the stream into Parquet files under ``folder``, read back."""
    query = stream.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{folder}/out")


def run_updates(stream: DataFrame, folder: str, keys: list[str]) -> DataFrame:
    """All that has arrived so far, through a stream in update mode (sessions: complete) into a folder of files for each batch; read back as the latest row of each key.

    A batch that is repeated replaces its own folder, and nothing goes to the driver.
    """
    mode = "complete" if "session_start" in keys else "update"
    query = stream.writeStream.foreachBatch(batch_sink(f"{folder}/out")).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark = stream.sparkSession
    rows = spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])).parquet(f"{folder}/out")
    rest = [c for c in stream.columns if c not in keys]
    if mode == "complete":
        last = rows.agg(F.max("batch").alias("batch"))
        return rows.join(F.broadcast(last), "batch").select(*stream.columns)
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("x")).select(*keys, "x.*").select(*stream.columns)
