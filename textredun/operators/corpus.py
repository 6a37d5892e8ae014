"""Reports over whole corpora: mean scores by split, language and tier, and scores against length."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def with_split(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of labelled documents with ``split``: clean is quality 1, all else noisy."""
    y = labels.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    return docs.join(y, "doc_id").withColumn("split", F.when(F.col("quality") == 1, "clean").otherwise("noisy")).drop("quality")


def by_language(rows: DataFrame, scores: Sequence[str]) -> DataFrame:
    """``lang, tier, split, n_docs`` and of each score its number, sum and mean: everything the reports below are made of, one row a language and split.

    A language is high-resource if it has more clean documents than languages have on average, so there are
    both tiers at any size unless all languages are alike.
    """
    parts = [x for s in scores for x in (F.count(s).alias(f"n_{s}"), F.sum(s).alias(f"sum_{s}"), F.avg(s).alias(s))]
    cells = rows.groupBy("lang", "split").agg(F.count(F.lit(1)).alias("n_docs"), *parts)
    clean = F.sum(F.when(F.col("split") == "clean", F.col("n_docs")).otherwise(0))
    cells = cells.withColumn("clean", clean.over(Window.partitionBy("lang")))
    mean = F.sum(F.when(F.col("split") == "clean", F.col("n_docs")).otherwise(0)).over(Window.partitionBy()) / F.size(F.collect_set(F.coalesce("lang", F.lit(""))).over(Window.partitionBy()))
    return cells.withColumn("tier", F.when(F.col("clean") > mean, "high").otherwise("low")).drop("clean")


def corpus_report(rows: DataFrame, scores: Sequence[str]) -> DataFrame:
    """Mean of each score over documents (``micro_``) and over languages (``macro_``) by split and tier, with all subtotals (NULL: all)."""
    return report_of(rows.groupBy("split", "tier", "lang").agg(F.count(F.lit(1)).alias("n_docs"), *[x for s in scores for x in (F.count(s).alias(f"n_{s}"), F.sum(s).alias(f"sum_{s}"), F.avg(s).alias(s))]), scores)


def report_of(cells: DataFrame, scores: Sequence[str]) -> DataFrame:
    """The same from the rows of ``by_language``."""
    return cells.cube("split", "tier").agg(
        F.sum("n_docs").alias("n_docs"),
        F.countDistinct("lang").alias("n_langs"),
        *[F.try_divide(F.sum(f"sum_{s}"), F.sum(f"n_{s}")).alias(f"micro_{s}") for s in scores],
        *[F.avg(s).alias(f"macro_{s}") for s in scores],
    )


def tier_gap(cells: DataFrame, scores: Sequence[str]) -> DataFrame:
    """Clean text of the languages with few documents beside noisy text of those with many: two rows of ``micro`` means."""
    two = cells.where("(split = 'clean' AND tier = 'low') OR (split = 'noisy' AND tier = 'high')")
    return two.groupBy("split", "tier").agg(F.sum("n_docs").alias("n_docs"), *[F.try_divide(F.sum(f"sum_{s}"), F.sum(f"n_{s}")).alias(s) for s in scores])


def approximate_profile(grams: DataFrame, *by: str) -> DataFrame:
    """Rough size of a corpus's vocabulary from exploded ``gram`` rows: one pass, a sketch per task; off by 2% as a rule."""
    return grams.groupBy(*by).agg(F.count(F.lit(1)).alias("n_grams"), F.approx_count_distinct("gram", 0.02).alias("n_types"))


def score_quantiles(scored: DataFrame, accuracy: int = 1000) -> DataFrame:
    """Approximate 5, 25, 50, 75 and 95% points of each setting's scores."""
    q = F.percentile_approx("score", [0.05, 0.25, 0.5, 0.75, 0.95], accuracy)
    return scored.where("valid").groupBy("signature").agg(F.count(F.lit(1)).alias("n_docs"), q.alias("q")).select("signature", "n_docs", *[F.col("q")[i].alias(f"p{p}") for i, p in enumerate((5, 25, 50, 75, 95))])


def boundary_summary(points: DataFrame, width: int = 500) -> DataFrame:
    """Per stretch of length and class: documents, mean score and how many pass the boundary."""
    return points.groupBy((F.floor(F.col("n_chars") / width) * width).alias("from_chars"), "label_class").agg(
        F.count(F.lit(1)).alias("n_docs"), F.avg("score").alias("mean_score"), F.sum(F.col("is_natural").cast("bigint")).alias("n_natural")
    )
