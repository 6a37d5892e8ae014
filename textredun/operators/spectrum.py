"""Spectra of documents: for each text and n-gram length, how many distinct n-grams (v) occur how often (c).

Three strategies give the same rows.  ``arrow`` counts in numpy inside each task, all lengths
in one pass, without a shuffle; it is the one for large data.  ``native`` does so with array
functions only.  ``relational`` explodes and groups, after moving each text once.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from textredun.operators import kernel

BENCHMARK_CAP = 5000  # what labelled benchmark texts may be cut to; nothing is cut unless asked for
COLUMNS = "unit string, n int, n_total bigint, n_types bigint, spectrum array<struct<c: bigint, v: bigint>>"
Spec = tuple[str, int]


def require_columns(df: DataFrame, *names: str) -> None:
    missing = [c for c in names if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")


def id_field(df: DataFrame) -> str:
    """``doc_id`` with its type: identifiers of any type are carried through."""
    return f"doc_id {df.schema['doc_id'].dataType.simpleString()}"


def capped(text: Column, cap: int | None = None) -> Column:
    """The first ``cap`` code points."""
    return text if cap is None else F.substring(text, 1, cap)


def cap_text(df: DataFrame, max_chars: int | None = BENCHMARK_CAP, text_col: str = "text") -> DataFrame:
    return df.withColumn(text_col, capped(F.col(text_col), max_chars))


def char_ngrams(text: Column, n: int, step: int = 512) -> Column:
    """All character n-grams as an array; empty for shorter texts.

    A substring is found by counting from the start of its string, so the text is first cut into
    stretches of ``step`` places: the time stays in proportion to the text.
    """

    def within(start: Column) -> Column:
        places = F.sequence(F.lit(1), F.least(F.lit(step), F.length(text) - (n - 1) - start))
        return _bind(F.substring(text, start + 1, F.lit(step + n - 1)), lambda part: F.transform(places, lambda i: F.substring(part, i, F.lit(n))))

    starts = F.sequence(F.lit(0), F.length(text) - n, F.lit(step))
    return F.when(F.length(text) >= n, F.flatten(F.transform(starts, within))).otherwise(F.array().cast("array<string>"))


def tokens(text: Column) -> Column:
    """What white space parts."""
    return F.filter(F.split(text, r"\s+"), lambda x: x != "")


def line_units(text: Column) -> Column:
    return F.split(text, "\n")


def joined_ngrams(units: Column, n: int, glue: str = " ") -> Column:
    """n-grams of an array of units, each joined to one string."""
    return F.when(F.size(units) >= n, F.transform(F.sequence(F.lit(1), F.size(units) - (n - 1)), lambda i: F.array_join(F.slice(units, i, F.lit(n)), glue))).otherwise(F.array().cast("array<string>"))


def token_ngrams(text: Column, n: int) -> Column:
    return joined_ngrams(tokens(text), n)


def grams_of(text: Column, unit: str, n: int) -> Column:
    if unit == "char":
        return char_ngrams(text, n)
    if unit == "token":
        return token_ngrams(text, n)
    if unit == "line":
        return joined_ngrams(line_units(text), n, "\n")
    raise ValueError(f"unknown unit {unit!r}")


def _texts(df: DataFrame, cap: int | None, id_col: str, text_col: str) -> DataFrame:
    require_columns(df, id_col, text_col)
    return df.select(F.col(id_col).alias("doc_id"), capped(F.col(text_col), cap).alias("text"))


def _arrow(rows: DataFrame, specs: Sequence[Spec]) -> DataFrame:
    by_unit: dict[str, list[int]] = {}
    for unit, n in specs:
        by_unit.setdefault(unit, []).append(n)

    def run(batches):
        for whole in batches:
            for begin, texts in kernel.slices([t or "" for t in whole.column(1).to_pylist()]):
                b = whole.slice(begin, len(texts))
                for unit, lengths in by_unit.items():
                    codes, ends = kernel.units_of(texts, unit)
                    for n, total, types, cut, c, v in kernel.spectra_of(codes, ends, lengths):
                        entries = pa.StructArray.from_arrays([pa.array(c), pa.array(v)], ["c", "v"])
                        yield pa.RecordBatch.from_arrays(
                            [b.column(0), pa.array([unit] * b.num_rows), pa.array(np.full(b.num_rows, n, np.int32)), pa.array(total), pa.array(types), pa.ListArray.from_arrays(pa.array(cut.astype(np.int32)), entries)],
                            ["doc_id", "unit", "n", "n_total", "n_types", "spectrum"],
                        )

    return rows.mapInArrow(run, f"{id_field(rows)}, {COLUMNS}")


def _bind(value: Column, use) -> Column:
    """``use(value)`` with the value computed once, not at each mention."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _runs(ordered: Column) -> Column:
    """Lengths of the runs of equal neighbours in an array."""
    starts = F.filter(F.sequence(F.lit(1), F.size(ordered)), lambda i: (i == 1) | (F.get(ordered, i - 1) != F.get(ordered, i - 2)))
    return _bind(starts, lambda s: F.zip_with(s, F.concat(F.slice(s, F.lit(2), F.size(s)), F.array(F.size(ordered) + 1)), lambda a, b: (b - a).cast("bigint")))


def _native(rows: DataFrame, specs: Sequence[Spec]) -> DataFrame:
    empty = F.array().cast("array<struct<c: bigint, v: bigint>>")

    def spectrum(counts: Column) -> Column:
        ordered = F.sort_array(counts, asc=False)
        return _bind(ordered, lambda o: F.zip_with(F.array_distinct(o), _runs(o), lambda c, v: F.struct(c.alias("c"), v.alias("v"))))

    parts = []
    for unit, n in specs:
        text = F.coalesce(F.col("text"), F.lit(""))
        row = _bind(
            F.array_sort(grams_of(text, unit, n)),
            lambda g: F.struct(F.size(g).cast("bigint").alias("n_total"), F.when(F.size(g) > 0, spectrum(_runs(g))).otherwise(empty).alias("spectrum")),
        )
        parts.append(F.struct(F.lit(unit).alias("unit"), F.lit(n).alias("n"), row.alias("row")))
    wide = rows.select("doc_id", F.explode(F.array(*parts)).alias("s"))
    types = F.aggregate("s.row.spectrum", F.lit(0).cast("bigint"), lambda a, e: a + e["v"])
    return wide.select("doc_id", "s.unit", "s.n", "s.row.n_total", types.alias("n_types"), F.col("s.row.spectrum").alias("spectrum"))


def _relational(rows: DataFrame, specs: Sequence[Spec]) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    marked = rows.withColumn("row_id", F.monotonically_increasing_id()).repartition("row_id")
    out = None
    for unit, n in specs:
        grams = marked.select("row_id", "doc_id", F.explode_outer(grams_of(text, unit, n)).alias("gram"))
        counts = grams.groupBy("row_id", "doc_id", "gram").agg(F.count("gram").alias("c"))
        levels = counts.where("c > 0 OR gram IS NULL").groupBy("row_id", "doc_id", "c").agg(F.count(F.lit(1)).alias("v"))
        entry = F.when(F.col("c") > 0, F.struct("c", "v"))
        one = levels.groupBy("row_id", "doc_id").agg(F.sum(F.col("c") * F.col("v")).alias("n_total"), F.sum(F.when(F.col("c") > 0, F.col("v")).otherwise(0)).alias("n_types"), F.sort_array(F.collect_list(entry), asc=False).alias("spectrum"))
        one = one.select("doc_id", F.lit(unit).alias("unit"), F.lit(n).alias("n"), "n_total", "n_types", "spectrum")
        out = one if out is None else out.unionByName(one)
    return out


def spectra(df: DataFrame, specs: Sequence[Spec], strategy: str = "arrow", cap: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, unit, n, n_total, n_types, spectrum`` for each row of ``df`` and each (unit, n) of ``specs``.

    A NULL text counts as an empty one: no n-grams, an empty spectrum.  Rows with the same id
    are counted apart.  Texts are read whole unless ``cap`` says how many code points to keep.
    """
    specs = list(dict.fromkeys((u, int(n)) for u, n in specs))
    if not specs or any(n < 1 for _, n in specs):
        raise ValueError("specs must name at least one (unit, n), with n of 1 or more")
    rows = _texts(df, cap, id_col, text_col)
    ways = {"arrow": _arrow, "native": _native, "relational": _relational}
    if strategy not in ways:
        raise ValueError(f"unknown strategy {strategy!r}")
    return ways[strategy](rows, specs)


def line_spectra(lines: DataFrame, key: str, order: Sequence[str], line: Column, n: int) -> DataFrame:
    """Spectra (``doc_id``: the key) of character n-grams of documents that are the lines of a key in order, joined by line ends.

    No document is ever put together: each line is counted with the first n - 1 characters of what
    follows it, so a document may be longer than any row.  ``order`` must tell the lines of a key apart.
    NULL lines are left out.
    """
    rows = lines.select(F.col(key).alias("doc_id"), *[F.col(c).alias(f"o{i}") for i, c in enumerate(order)], line.alias("line")).where("line IS NOT NULL")
    w = Window.partitionBy("doc_id").orderBy(*[f"o{i}" for i in range(len(order))])
    after = [F.coalesce(F.concat(F.lit("\n"), F.substring(F.lead("line", i).over(w), 1, n)), F.lit("")) for i in range(1, n + 1)]
    whole = rows.select("doc_id", (F.length("line") + F.when(F.lead("line", 1).over(w).isNotNull(), 1).otherwise(0)).alias("own"), F.concat("line", *after).alias("t"))
    places = F.explode(F.when(F.length("t") >= n, F.sequence(F.lit(1), F.least("own", F.length("t") - (n - 1)))))
    grams = whole.where("own > 0").select("doc_id", "t", places.alias("i")).select("doc_id", F.substring("t", F.col("i"), F.lit(n)).alias("gram"))
    levels = grams.groupBy("doc_id", "gram").agg(F.count(F.lit(1)).alias("c")).groupBy("doc_id", "c").agg(F.count(F.lit(1)).alias("v"))
    return _gathered(levels, "char", n)


def _gathered(levels: DataFrame, unit: str, n: int) -> DataFrame:
    """Spectra from rows ``doc_id, c, v``."""
    one = levels.groupBy("doc_id").agg(F.sum(F.col("c") * F.col("v")).alias("n_total"), F.sum("v").alias("n_types"), F.sort_array(F.collect_list(F.struct("c", "v")), asc=False).alias("spectrum"))
    return one.select("doc_id", F.lit(unit).alias("unit"), F.lit(n).alias("n"), "n_total", "n_types", "spectrum")


def pooled_counts(df: DataFrame, unit: str = "char", n: int = 3, group: str | None = None, cap: int | None = None, text_col: str = "text") -> DataFrame:
    """``doc_id, gram, c``: how often each n-gram occurs in all texts of a group together (``doc_id`` is the group; NULL without one).

    One shuffle of counts already added up inside each task; an n-gram never spans two texts.
    """
    of = F.lit(None).cast("string") if group is None else F.col(group)
    rows = df.select(of.alias("doc_id"), capped(F.col(text_col), cap).alias("text")).where("text IS NOT NULL")
    return rows.select("doc_id", F.explode(grams_of(F.col("text"), unit, n)).alias("gram")).groupBy("doc_id", "gram").agg(F.count(F.lit(1)).alias("c"))


def pooled_spectra(counts: DataFrame, unit: str = "char", n: int = 3) -> DataFrame:
    """Spectra of whole groups from ``pooled_counts``. Spectra of texts can't simply be added: equal n-grams of two texts are one."""
    return _gathered(counts.groupBy("doc_id", "c").agg(F.count(F.lit(1)).alias("v")), unit, n)


def corpus_histogram(counts: DataFrame, top: int | None = None) -> DataFrame:
    """``doc_id, gram, cnt, rank`` of each group of ``pooled_counts``, by falling count, equal counts by n-gram."""
    ranked = counts.select("doc_id", "gram", F.col("c").alias("cnt"), F.row_number().over(Window.partitionBy("doc_id").orderBy(F.desc("c"), "gram")).alias("rank"))
    return ranked if top is None else ranked.where(F.col("rank") <= top)


def gram_histogram(df: DataFrame, unit: str = "char", n: int = 6, top: int | None = None, cap: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, gram, cnt, rank``: the n-grams of each document by falling count, equal counts by n-gram."""
    rows = _texts(df, cap, id_col, text_col).where("text IS NOT NULL")
    counts = rows.select("doc_id", F.explode(grams_of(F.col("text"), unit, n)).alias("gram")).groupBy("doc_id", "gram").agg(F.count(F.lit(1)).alias("cnt"))
    ranked = counts.withColumn("rank", F.row_number().over(Window.partitionBy("doc_id").orderBy(F.desc("cnt"), "gram")))
    return ranked if top is None else ranked.where(F.col("rank") <= top)


def window_ttr(df: DataFrame, unit: str = "token", width: int = 50, stride: int = 1, cap: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_windows, score``: mean share of distinct units over windows of ``width`` units, every ``stride`` units.

    A window shorter than ``width`` counts only where it is the document's only one; no units: NULL.  The last window
    ends where the text does, so every unit is in one.  With a stride of 1 the time grows with the units, not with the width.
    """

    def moving(u: list[str]) -> tuple[int, float | None]:
        """Windows and mean share for a stride of 1: each unit counts in the windows that it is the first of its kind in."""
        if not u:
            return 0, None
        w = min(width, len(u))
        last, before, total = len(u) - w, {}, 0
        for i, x in enumerate(u):
            total += max(0, min(i, last) - max(before.get(x, -1) + 1, i - w + 1) + 1)
            before[x] = i
        return last + 1, total / (w * (last + 1))

    def run(batches):
        for b in batches:
            windows, score = [], []
            for t in b.column(1).to_pylist():
                u = (list(t) if unit == "char" else kernel.TOKEN.findall(t) if unit == "token" else t.split("\n")) if t else []
                if stride == 1:
                    n, mean = moving(u)
                    windows.append(n)
                    score.append(mean)
                    continue
                last = max(len(u) - width, 0)
                starts = sorted({*range(0, last + 1, stride), last}) if u else ()
                shares = [len(set(u[s : s + width])) / len(u[s : s + width]) for s in starts]
                windows.append(len(shares))
                score.append(sum(shares) / len(shares) if shares else None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(windows, pa.int64()), pa.array(score, pa.float64())], ["doc_id", "n_windows", "score"])

    rows = _texts(df, cap, id_col, text_col)
    return rows.mapInArrow(run, f"{id_field(rows)}, n_windows bigint, score double")
