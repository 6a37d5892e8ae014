"""Documents from files, and from tables whose rows make up documents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from textredun.operators.spectrum import require_columns

FORMATS = ("parquet", "orc", "json", "csv", "text", "wholetext")


def read_documents(spark: SparkSession, path: str | list[str], format: str = "parquet", id_col: str = "doc_id", text_col: str = "text", schema=None, **options) -> DataFrame:
    """``doc_id, text`` and the file's other columns. Text formats have no ids: a digest of file and text stands in (``wholetext``: one document a file, else one a line)."""
    if format not in FORMATS:
        raise ValueError(f"unknown format {format!r}; known are {FORMATS}")
    reader = spark.read.options(**options)
    if format in ("text", "wholetext"):
        rows = reader.text(path, wholetext=format == "wholetext")
        return rows.select(F.xxhash64(F.input_file_name(), "value").alias("doc_id"), F.col("value").alias("text"))
    if schema is not None:
        reader = reader.schema(schema)
    if format == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    df = reader.format(format).load(path)
    require_columns(df, id_col, text_col)
    return df.withColumnsRenamed({id_col: "doc_id", text_col: "text"})


def spread(df: DataFrame) -> DataFrame:
    """For tables of a few files whose row groups can't be split, on many cores: the rows dealt out over all of them. Moves every text once; a table of as many files as there are cores stays as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if len(df.inputFiles()) < cores else df


def _joined(df: DataFrame, key: str, order: list[str], line: Column, glue: str = "\n") -> DataFrame:
    """One document per key: its rows' lines in order."""
    lines = F.transform(F.array_sort(F.collect_list(F.struct(*order, line.alias("line")))), lambda x: x["line"])
    return df.groupBy(F.col(key)).agg(F.array_join(lines, glue).alias("text"))


def catalogue_line() -> Column:
    return F.concat_ws(" ", "p_name", "p_type", F.lit("size"), F.col("p_size").cast("string"), F.concat(F.lit("$"), F.format_string("%.2f", "p_retailprice")))


def catalogue_docs(part: DataFrame) -> DataFrame:
    """A price list per brand as one text: one line ``name type size N $price`` per item, by key. For brands whose lists are too long for a row, see ``spectrum.line_spectra``."""
    return _joined(part, "p_brand", ["p_partkey"], catalogue_line()).withColumnRenamed("p_brand", "doc_id")


def event_log_docs(events: DataFrame) -> DataFrame:
    """A log file per user: one line ``time type value`` per event, by time and id."""
    line = F.concat_ws(" ", F.date_format("ts", "yyyy-MM-dd HH:mm:ss"), "event_type", F.format_string("%.2f", "value"))
    return _joined(events, "user_id", ["ts", "event_id"], line).withColumnRenamed("user_id", "doc_id")


def conversation_docs(conversations: DataFrame, role: str | None = None) -> DataFrame:
    """A document per conversation: its turns (of one role, or all) in order."""
    rows = conversations if role is None else conversations.where(F.col("role") == role)
    return _joined(rows, "conv_id", ["turn"], F.coalesce("text", F.lit(""))).withColumnRenamed("conv_id", "doc_id")


def page_docs(pages: DataFrame) -> DataFrame:
    """``doc_id, variant, text``: each page's HTML as it is, without tags, and its article alone."""
    bare = lambda c: F.btrim(F.regexp_replace(F.regexp_replace(F.regexp_replace(c, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), r"<[^>]*>", " "), r"[ \t\r\n]+", " "))
    article = F.regexp_extract("html", r"(?s)<article[^>]*>(.*?)</article>", 1)
    variants = F.array(*[F.struct(F.lit(n).alias("variant"), t.alias("text")) for n, t in (("html", F.col("html")), ("stripped", bare(F.col("html"))), ("article", bare(article)))])
    return pages.select(F.col("page_id").alias("doc_id"), F.explode(variants).alias("x")).select("doc_id", "x.*")
