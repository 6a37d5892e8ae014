"""Accuracy measures. The positive class is natural text, so a document is called natural if its score is at most the threshold."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: 97.5% points of Student's t by degrees of freedom
T_975 = {1: 12.706205, 2: 4.302653, 3: 3.182446, 4: 2.776445, 5: 2.570582, 6: 2.446912, 7: 2.364624, 8: 2.306004, 9: 2.262157, 14: 2.144787, 19: 2.093024, 29: 2.045230, 49: 2.009575, 99: 1.984217}


def _ratio(a, b) -> Column:
    return F.try_divide(a, b)


def f1(tp="tp", fp="fp", fn="fn") -> Column:
    tp, fp, fn = (F.col(x) if isinstance(x, str) else x for x in (tp, fp, fn))
    return _ratio(2 * tp, 2 * tp + fp + fn)


def p4(tp="tp", fp="fp", fn="fn", tn="tn") -> Column:
    """Harmonic mean of precision, recall, specificity and negative predictive value."""
    tp, fp, fn, tn = (F.col(x) if isinstance(x, str) else x for x in (tp, fp, fn, tn))
    return _ratio(4 * tp * tn, 4 * tp * tn + (tp + tn) * (fp + fn))


def confusion(df: DataFrame, *by: str) -> DataFrame:
    """Weighted ``tp, fp, fn, tn`` of rows ``is_natural`` (truth), ``predicted`` and ``weight``."""
    cell = lambda truth, said: F.coalesce(F.sum(F.when((F.col("is_natural") == truth) & (F.col("predicted") == said), F.col("weight").cast("double"))), F.lit(0.0))
    return df.groupBy(*by).agg(cell(True, True).alias("tp"), cell(False, True).alias("fp"), cell(True, False).alias("fn"), cell(False, False).alias("tn"))


def measures(conf: DataFrame) -> DataFrame:
    """Confusion counts with precision, recall, specificity, npv, accuracy, f1 and p4; NULL where nothing is counted."""
    tp, fp, fn, tn = (F.col(c) for c in ("tp", "fp", "fn", "tn"))
    return conf.select(
        "*",
        _ratio(tp, tp + fp).alias("precision"),
        _ratio(tp, tp + fn).alias("recall"),
        _ratio(tn, tn + fp).alias("specificity"),
        _ratio(tn, tn + fn).alias("npv"),
        _ratio(tp + tn, tp + fp + fn + tn).alias("accuracy"),
        f1().alias("f1"),
        p4().alias("p4"),
    )


def base_rate_purity(prior, recall, fpr):
    """Share of natural text among what passes, if a share ``prior`` of all is natural. Numbers or columns."""
    return prior * recall / (prior * recall + (1 - prior) * fpr)


def relative_gain(a, b):
    return a / b - 1


def t_975(df: int) -> float:
    """97.5% point of Student's t (interpolated in 1/df between tabled values)."""
    if df in T_975:
        return T_975[df]
    low = max(k for k in T_975 if k <= df)
    high = min((k for k in T_975 if k >= df), default=None)
    x, a, b = 1 / df, 1 / low, 1 / high if high else 0.0
    return T_975[low] + ((T_975[high] if high else 1.959964) - T_975[low]) * (a - x) / (a - b)


def mean_with_interval(df: DataFrame, value: str, *by: str) -> DataFrame:
    """Mean of ``value`` and half the width of its 95% interval (``ci95``, by Student's t; NULL for a single value)."""
    out = df.groupBy(*by).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
    points = F.create_map(*[F.lit(x) for k in range(1, 200) for x in (k, t_975(k))])
    return out.withColumn("ci95", F.coalesce(F.try_element_at(points, (F.col("n") - 1).cast("int")), F.lit(1.959964)) * F.col("sd") / F.sqrt("n")).drop("sd")


def bootstrap_interval(values: list[float], draws: int = 2000, seed: int = 0) -> tuple[float, float, float]:
    """(mean, low, high): percentile interval of 95% over seeded resamples of a few values."""
    import numpy as np

    x = np.asarray(values, dtype=float)
    means = np.random.default_rng(seed).choice(x, (draws, len(x))).mean(axis=1)
    return float(x.mean()), float(np.quantile(means, 0.025)), float(np.quantile(means, 0.975))


def run_cost(result: DataFrame, docs: DataFrame, spectra: DataFrame, text_col: str = "text") -> DataFrame:
    """What a run costs: ``n_docs, n_chars, seconds, docs_per_second, chars_per_second, spectrum_bytes_per_doc, shuffles``.

    ``result`` is run to its end and thrown away; ``docs`` are what it reads, ``spectra`` what would be kept for reuse
    (16 bytes an entry); shuffles are those of its plan.
    """
    import contextlib
    import io
    import time

    plan = io.StringIO()
    with contextlib.redirect_stdout(plan):
        result.explain()
    began = time.time()
    result.write.format("noop").mode("overwrite").save()
    seconds = F.lit(time.time() - began)
    size = docs.agg(F.count(F.lit(1)).alias("n_docs"), F.coalesce(F.sum(F.length(text_col).cast("bigint")), F.lit(0)).alias("n_chars"))
    kept = spectra.agg(F.avg(F.size("spectrum") * 16.0).alias("spectrum_bytes_per_doc"))
    return size.crossJoin(F.broadcast(kept)).select("n_docs", "n_chars", seconds.alias("seconds"), (F.col("n_docs") / seconds).alias("docs_per_second"), (F.col("n_chars") / seconds).alias("chars_per_second"), "spectrum_bytes_per_doc", F.lit(plan.getvalue().count("Exchange")).alias("shuffles"))
