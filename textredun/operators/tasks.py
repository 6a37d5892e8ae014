"""The labelled benchmark: four classes, two tasks, two halves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from textredun.operators.spectrum import capped, tokens

TASKS = {"repeat": ("natural", "repetitive"), "noise": ("natural", "repetitive", "noise")}


def stutter_share(text: Column) -> Column:
    """Share of words that equal the word before."""
    w = tokens(text)
    pairs = F.zip_with(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, 2, F.size(w)), lambda a, b: (a == b).cast("int"))
    return F.try_divide(F.aggregate(pairs, F.lit(0), lambda a, x: a + x), F.size(w))


def classified(docs: DataFrame, labels: DataFrame, cap: int | None = None, unsure: bool = True) -> DataFrame:
    """``doc_id, text, lang, label_class, half``.

    Quality 1 is ``natural``; quality 0 is ``repetitive`` if over 0.3 of the words repeat the one before, else
    ``noise``; documents without a label are ``unsure``, and left out where ``unsure`` is False.  ``half`` (tune or
    test) hangs on the whole text alone, so copies never part.  ``cap`` cuts texts to so many code points.
    """
    y = labels.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    text = capped(F.col("text"), cap)
    # what needs the text is computed before the join, so that counts of classes move no texts
    rows = docs.select("doc_id", text.alias("text"), "lang", half_of(F.md5("text")).alias("half"), (stutter_share(text) > 0.3).alias("stutters"))
    label = F.when(F.col("quality") == 1, "natural").when(F.col("quality").isNull(), "unsure").when(F.col("stutters"), "repetitive").otherwise("noise")
    return rows.join(y, "doc_id", "left" if unsure else "inner").select("doc_id", "text", "lang", label.alias("label_class"), "half").where(F.lit(unsure) | (F.col("label_class") != "unsure"))


def half_of(digest: Column) -> Column:
    return F.when(F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint") % 2 == 0, "tune").otherwise("test")


def task(classes: DataFrame, name: str, balanced: bool = True, natural_share: float = 0.5) -> DataFrame:
    """Rows of one task with ``is_natural`` and ``weight``.

    With ``balanced``, the weights of each half make natural text the share ``natural_share``
    of it, so scores don't hang on how many of each were labelled.
    """
    rows = classes.where(F.col("label_class").isin(*TASKS[name])).withColumn("is_natural", F.col("label_class") == "natural")
    if not balanced:
        return rows.withColumn("weight", F.lit(1.0))
    n = rows.groupBy("half", "is_natural").agg(F.count(F.lit(1)).alias("n"))
    share = F.when(F.col("is_natural"), F.lit(natural_share)).otherwise(F.lit(1 - natural_share))
    weights = n.select("half", "is_natural", (share / F.col("n")).alias("weight"))
    return rows.join(F.broadcast(weights), ["half", "is_natural"])


def per_language_sample(classes: DataFrame, most: int = 6) -> DataFrame:
    """At most ``most`` natural documents of each language, chosen by a digest of their text."""
    w = Window.partitionBy("lang").orderBy(F.md5("text"), "doc_id")
    return classes.where("label_class = 'natural'").withColumn("place", F.row_number().over(w)).where(F.col("place") <= most)
