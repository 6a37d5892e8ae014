"""Scores for SQL users.

``redundancy(text, signature)`` counts anew at each call: for many settings over the same
texts, count once with ``spectra`` and score that.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from textredun.functions.signature import parse_signature
from textredun.operators import kernel, metrics


def score_texts(texts: list[str | None], name: str) -> list[float | None]:
    """Scores of texts under a signature."""
    return [None if x != x else float(x) for x in metrics.score_texts(texts, [parse_signature(name)])[1][:, 0]]


@F.pandas_udf(T.DoubleType())
def redundancy(text: pd.Series, name: pd.Series) -> pd.Series:
    out = pd.Series([None] * len(text), dtype="float64")
    for one, rows in text.groupby(name.to_numpy()).groups.items():
        out[rows] = score_texts([None if pd.isna(t) else t for t in text[rows]], one)
    return out


@F.udtf(returnType=T.StructType().add("gram", T.StringType()).add("position", T.IntegerType()))
class Ngrams:
    """``ngrams(text, unit, n)``: every n-gram of a text with where it begins, from 1."""

    def eval(self, text: str, unit: str, n: int):
        if text is not None:
            units = list(text) if unit == "char" else kernel.TOKEN.findall(text) if unit == "token" else text.split("\n")
            glue = {"char": "", "token": " "}.get(unit, "\n")
            for i in range(len(units) - n + 1):
                yield glue.join(units[i : i + n]), i + 1


@F.udtf(returnType=T.StructType().add("c", T.LongType()).add("v", T.LongType()))
class Spectrum:
    """``spectrum(text, unit, n)``: how many distinct n-grams (v) occur how often (c)."""

    def eval(self, text: str, unit: str, n: int):
        if text is not None:
            for _, _, _, _, c, v in kernel.spectra_of(*kernel.units_of([text], unit), [n]):
                yield from zip(c.tolist(), v.tolist())


def register(spark: SparkSession) -> None:
    """Makes ``redundancy``, ``ngrams`` and ``spectrum`` known to SQL."""
    spark.udf.register("redundancy", redundancy)
    spark.udtf.register("ngrams", Ngrams)
    spark.udtf.register("spectrum", Spectrum)
