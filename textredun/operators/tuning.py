"""Thresholds and grid search.

One job scores all labelled texts under all settings, reading each text once; thresholds then come from
running counts over the distinct scores of each setting, in one window, without a loop.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from textredun.functions.signature import Ensemble, Setting, members, signature
from textredun.operators import measures as ms
from textredun.operators import metrics, tasks
from textredun.sources.shared import written

OBJECTIVES = {"f1": ms.f1, "p4": ms.p4}
KEY = ["signature"]


def classify(scored: DataFrame, threshold: float | str) -> DataFrame:
    """``scored`` with ``is_natural``: NULL where the score is not valid."""
    t = F.col(threshold) if isinstance(threshold, str) else F.lit(threshold)
    return scored.withColumn("is_natural", F.when(F.col("valid"), F.col("score") <= t))


def with_verdict(docs: DataFrame, s: Setting | Ensemble, threshold: float | DataFrame, score: str = "score", verdict: str = "is_natural", places: int | None = None, text_col: str = "text") -> DataFrame:
    """``docs`` with its score and verdict (NULL where the score is not valid), row by row: no join, no shuffle.

    ``threshold`` is a number, or a table of one row with a column ``threshold``.  ``places`` rounds scores before they are
    compared, as ``grid_results`` and ``learned_thresholds`` do.
    """
    rows = metrics.with_scores(docs, {score: s}, text_col)
    if places is not None:
        rows = rows.withColumn(score, rounded_score(score, places))
    if isinstance(threshold, DataFrame):
        held = "threshold"
        while held.lower() in {c.lower() for c in rows.columns}:
            held = "_" + held
        rows = rows.crossJoin(F.broadcast(threshold.select(F.col("threshold").alias(held))))
        return rows.withColumn(verdict, F.col(score) <= F.col(held)).drop(held)
    return rows.withColumn(verdict, F.col(score) <= F.lit(float(threshold)))


def filter_natural(docs: DataFrame, s: Setting | Ensemble, threshold: float | DataFrame, keep_invalid: bool = True, places: int | None = None, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose score is at most the threshold; texts too short to score stay unless told otherwise. Ids play no part."""
    score, verdict = _unused(docs, "score", "is_natural")
    kept = with_verdict(docs, s, threshold, score, verdict, places, text_col).where(F.coalesce(F.col(verdict), F.lit(keep_invalid)))
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns])


def partition_by_verdict(docs: DataFrame, s: Setting | Ensemble, threshold: float | DataFrame, places: int | None = None, text_col: str = "text") -> DataFrame:
    """``docs`` with ``score`` and ``is_natural``, rejects and all."""
    return with_verdict(docs, s, threshold, places=places, text_col=text_col)


def _unused(df: DataFrame, *names: str) -> list[str]:
    taken, out = {c.lower() for c in df.columns}, []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


def rounded_score(name: str, places: int = 6) -> Column:
    """A score at so many places; the nudge settles halves, so that equal scores stay equal whatever the order of sums."""
    return F.round(F.col(name) + 1e-10, places)


def threshold_curve(scored: DataFrame, by: Sequence[str] = KEY) -> DataFrame:
    """Confusion counts at every distinct score taken as threshold. ``scored`` has ``is_natural`` (truth), ``weight``, ``score`` and ``valid``."""
    by = list(by)
    side = lambda truth: F.sum(F.when(F.col("is_natural") == truth, F.col("weight")).otherwise(0.0))
    points = scored.where("valid").groupBy(*by, "score").agg(side(True).alias("pos"), side(False).alias("neg"))
    run = Window.partitionBy(*by).orderBy("score").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy(*by)
    curve = points.select(*by, F.col("score").alias("threshold"), F.sum("pos").over(run).alias("tp"), F.sum("neg").over(run).alias("fp"), F.sum("pos").over(whole).alias("all_pos"), F.sum("neg").over(whole).alias("all_neg"))
    return curve.withColumns({"fn": F.col("all_pos") - F.col("tp"), "tn": F.col("all_neg") - F.col("fp")}).drop("all_pos", "all_neg")


def tune_threshold(scored: DataFrame, objective: str = "f1", by: Sequence[str] = KEY) -> DataFrame:
    """The best threshold of each setting and its value; of equal ones the lowest."""
    curve = threshold_curve(scored, by).withColumn("value", F.round(OBJECTIVES[objective](), 12))
    best = F.max_by(F.struct("threshold", "value"), F.struct(F.coalesce("value", F.lit(-1.0)), -F.col("threshold"))).alias("best")
    return curve.groupBy(*by).agg(best).select(*by, "best.threshold", "best.value")


def evaluate(scored: DataFrame, thresholds: DataFrame, by: Sequence[str] = KEY) -> DataFrame:
    """Measures of each setting at its own threshold."""
    by = list(by)
    said = scored.where("valid").join(F.broadcast(thresholds.select(*by, "threshold")), by).withColumn("predicted", F.col("score") <= F.col("threshold"))
    return ms.measures(ms.confusion(said, *by))


def threshold_as_of(scored: DataFrame, versions: DataFrame, time: str = "at", by: Sequence[str] = KEY) -> DataFrame:
    """``scored`` (with a time column) and the ``threshold`` of the latest of ``versions`` (same columns, and ``threshold``) that is no later.

    Both go through one window by setting and time, versions first at equal times; rows before the first version get NULL.
    """
    by = list(by)
    left = scored.select(F.struct("*").alias("row"), *by, time, F.lit(None).cast("double").alias("threshold"), F.lit(1).alias("turn"))
    right = versions.select(F.lit(None).cast(left.schema["row"].dataType).alias("row"), *by, time, F.col("threshold").cast("double"), F.lit(0).alias("turn"))
    seen = Window.partitionBy(*by).orderBy(time, "turn").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.unionByName(right).withColumn("threshold", F.last("threshold", ignorenulls=True).over(seen))
    return both.where("turn = 1").select("row.*", "threshold")


def constant_baseline(rows: DataFrame) -> DataFrame:
    """Measures of calling everything natural."""
    return ms.measures(ms.confusion(rows.withColumn("predicted", F.lit(True))))


#: operating point -> (share of natural text that it is tuned for, objective)
OPERATING_POINTS = {"balanced_f1": (0.5, "f1"), "clean75_p4": (0.75, "p4")}


def rates(rows: DataFrame, by: Sequence[str] = KEY) -> DataFrame:
    """``*by, score, recall, alarms``: the shares of natural and of other rows that pass at each distinct score, of rows ``is_natural, score``.

    Counts are whole numbers, so the result does not hang on the order of rows.  Rows without a score are in no share.
    """
    by = list(by)
    points = rows.where("score IS NOT NULL").groupBy(*by, "score").agg(F.count_if("is_natural").alias("pos"), F.count_if(~F.col("is_natural")).alias("neg"))
    run = Window.partitionBy(*by).orderBy("score").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy(*by)
    return points.select(*by, "score", *[F.try_divide(F.sum(c).over(run), F.sum(c).over(whole)).alias(r) for c, r in (("pos", "recall"), ("neg", "alarms"))])


def point_value(share: float, objective: str) -> Column:
    """An objective at each row of ``rates``, for a share of natural text."""
    return F.round(_value(F.col("recall"), F.coalesce("alarms", F.lit(0.0)), share, objective), 12)


def best_thresholds(rows: DataFrame, cases: dict[str, tuple[float, str]], by: Sequence[str] = KEY) -> DataFrame:
    """``*by, case, threshold, value``: the best threshold for each case (share of natural text, objective) over rows ``is_natural, score``.

    The classes count by their shares, not by how many rows each has.  Counts are whole numbers, so the result
    does not hang on the order of rows.  NULL scores are left out; of equal thresholds the lowest wins.
    """
    by = list(by)
    value = {k: point_value(share, objective) for k, (share, objective) in cases.items()}
    best = rates(rows, by).groupBy(*by).agg(*[F.max_by(F.struct(F.lit(k).alias("case"), F.col("score").alias("threshold"), v.alias("value")), F.struct(F.coalesce(v, F.lit(-1.0)), -F.col("score"))).alias(k) for k, v in value.items()])
    return best.select(*by, F.inline(F.array(*cases)))


def _value(recall: Column, alarms: Column, share: float, objective: str) -> Column:
    tp, fp = share * recall, (1 - share) * alarms
    return OBJECTIVES[objective](tp, fp, share - tp, *([1 - share - fp] if objective == "p4" else []))


def learned_thresholds(docs: DataFrame, labels: DataFrame, settings: dict[str, Setting | Ensemble], task: str = "noise", cap: int | None = None, places: int = 6) -> DataFrame:
    """``name, operating_point, threshold, value`` of each setting, learned from the tune half of a task's labelled documents."""
    classes = tasks.classified(docs, labels, cap, unsure=False).where("half = 'tune'").where(F.col("label_class").isin(*tasks.TASKS[task]))
    rows = metrics.with_scores(classes, settings).select((F.col("label_class") == "natural").alias("is_natural"), F.inline(F.array(*[F.struct(F.lit(n).alias("name"), rounded_score(n, places).alias("score")) for n in settings])))
    return best_thresholds(rows, OPERATING_POINTS, ["name"]).withColumnRenamed("case", "operating_point")


# --- grids -----------------------------------------------------------------------------------------------


#: n-gram lengths and units that are averaged: name -> (unit, n)
MIXES = {
    "char:3-6": [("char", n) for n in (3, 4, 5, 6)],
    "char:4-5": [("char", 4), ("char", 5)],
    "char:5-6": [("char", 5), ("char", 6)],
    "char:6-8": [("char", n) for n in (6, 7, 8)],
    "char:4-8": [("char", n) for n in (4, 5, 6, 7, 8)],
    "char:6+token:1": [("char", 6), ("token", 1)],
    "char:5-6+token:1-2": [("char", 5), ("char", 6), ("token", 1), ("token", 2)],
}
POWERS = ({"k": 1.5}, {"k": 2.0}, {"k": 3.0}, {"g": "sq_entropy"})


def _spread_over(specs, base: Sequence[Setting], mixes: bool) -> list[Setting | Ensemble]:
    """Each setting of ``base`` at each spec, then as the mean over each mix of specs that are all there."""
    out: list[Setting | Ensemble] = [s.but(unit=u, n=n) for u, n in specs for s in base]
    wanted = [m for m in MIXES.values() if mixes and set(m) <= set(specs)]
    return out + [Ensemble(tuple(s.but(unit=u, n=n) for u, n in m)) for m in wanted for s in base]


def final_grid(lengths: Sequence[int] = (1, 2, 3, 4, 5, 6, 7, 8), lams=(0.0, 0.1, 1.0), asymptotes=(500.0, 1000.0, 2000.0, 5000.0, math.inf), mixes: bool = True) -> list[Setting | Ensemble]:
    """The restricted grid: no truncation, the nonlinearities and distances that did well, single lengths and mixes."""
    base = [Setting(metric="ttr", lam=lam) for lam in lams]
    for lam, a in itertools.product(lams, asymptotes):
        base += [Setting(lam=lam, asymptote=a, **g) for g in POWERS]
        base += [Setting(metric="zipf", lam=lam, asymptote=a, d=d, norm="ratio" if d in ("sq", "jsd") else "difference") for d in ("sq", "log")]
    return _spread_over([("char", n) for n in lengths] + [("token", 1), ("token", 2)], base, mixes)


def deep_grid(lengths: Sequence[int] = (1, 2, 3, 4, 5, 6, 7, 8, 10), lams=(0.0, 0.1, 1.0, 10.0), asymptotes=(500.0, 1000.0, 2000.0, 5000.0, math.inf), mixes: bool = True) -> list[Setting | Ensemble]:
    """The wide grid: truncation, stronger smoothing and every nonlinearity and distance as well."""
    cuts = [{}, {"eps": 1.0}, {"eps": 2.0}, {"top_k": 100}, {"top_k": 1000}]
    base = [Setting(metric="ttr", lam=lam, **cut) for lam, cut in itertools.product(lams, cuts)]
    for lam, cut, a in itertools.product(lams, cuts, asymptotes):
        base += [Setting(lam=lam, asymptote=a, **cut, **g) for g in (*POWERS, {"g": "entropy"})]
        base += [Setting(metric="zipf", lam=lam, asymptote=a, d=d, norm="ratio" if d in ("sq", "jsd", "abs") else "difference", **cut) for d in ("sq", "log", "sq_log", "jsd", "abs", "kl_pq", "kl_qp")]
    return _spread_over([("char", n) for n in lengths] + [("token", n) for n in (1, 2, 3)], base, mixes)


HELD_SCORES = 1 << 21  # scores to a batch, about
SETTING_COLUMNS = "setting int, signature string, metric string, unit string, n int, lengths string, lam double, eps double, top_k int, g string, k double, d string, asymptote double"


def settings_table(spark, settings: Sequence[Setting | Ensemble]) -> DataFrame:
    """One row per setting: its place, signature and parameters. Of an ensemble, ``n`` is NULL and ``lengths`` names the mix; ``unit`` is ``mixed`` where units differ."""
    known = {tuple(specs): name for name, specs in MIXES.items()}
    rows = []
    for i, x in enumerate(settings):
        s, specs = members(x)[0], tuple(m.spec for m in members(x))
        units = {u for u, _ in specs}
        one = len(specs) == 1
        rows.append((i, signature(x), s.metric, s.unit if len(units) == 1 else "mixed", s.n if one else None, f"{s.unit}:{s.n}" if one else known.get(specs, "+".join(f"{u}:{n}" for u, n in specs)), s.lam, s.eps, s.top_k, s.g if s.metric == "moment" else None, s.k if s.metric == "moment" and s.g == "pow" else None, s.d if s.metric == "zipf" else None, None if s.metric == "ttr" or math.isinf(s.asymptote) else s.asymptote))
    return spark.createDataFrame(rows, SETTING_COLUMNS)


def graded(docs: DataFrame, labels: DataFrame, settings: Sequence[Setting | Ensemble], cap: int | None = None, places: int = 6, extra: DataFrame | None = None) -> DataFrame:
    """``label_class, half, scores`` (rounded, in the order of the settings) of each labelled document: every text is read and counted once.

    ``extra`` has more texts (``text``) to be taken for repetitive ones.
    """
    rows = tasks.classified(docs, labels, cap, unsure=False).select("text", "label_class", "half")
    if extra is not None:
        rows = rows.unionByName(extra.select("text", F.lit("repetitive").alias("label_class"), tasks.half_of(F.md5("text")).alias("half")))
    scores = metrics.score_column(F.col("text"), [s.but(cap=cap) for s in settings]).alias("x")
    return rows.select("label_class", "half", scores).select("label_class", "half", F.transform("x.scores", lambda x: F.round(x + 1e-10, places)).alias("scores"))


def grid_results(docs: DataFrame, labels: DataFrame, settings: Sequence[Setting | Ensemble], task_names: Sequence[str] = ("repeat", "noise"), objective: str = "f1", cap: int | None = None, places: int = 6, extra: DataFrame | None = None) -> DataFrame:
    """``tuned_on, tested_on, signature, metric, ..., threshold, tune_value, test_f1``.

    Thresholds are tuned on the tune half of one task and tested on the test half of each; the classes of a half weigh the
    same.  Scores are written to the shared folder once and both halves read them there; from then on one shuffle by
    setting serves all counts.
    """
    conf, batch = docs.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    usual = conf.get(batch)
    # a worker holds the scores of a whole batch of texts under all settings
    conf.set(batch, str(max(1, min(int(usual) if int(usual) > 0 else HELD_SCORES, HELD_SCORES // max(1, len(settings))))))
    try:
        rows = written(graded(docs, labels, settings, cap, places, extra), "graded")
    finally:
        conf.set(batch, usual)
    tasks_of = {t: F.col("label_class").isin(*tasks.TASKS[t]) for t in task_names}
    good = F.col("label_class") == "natural"
    long = rows.select("half", *[(inside & side).alias(f"{t}_{k}") for t, inside in tasks_of.items() for k, side in (("pos", good), ("neg", ~good))], F.posexplode("scores").alias("setting", "score"))
    long = long.where("score IS NOT NULL").repartition("setting")
    counts = [f"{t}_{k}" for t in task_names for k in ("pos", "neg")]
    points = long.where("half = 'tune'").groupBy("setting", "score").agg(*[F.count_if(c).alias(c) for c in counts])
    run = Window.partitionBy("setting").orderBy("score").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy("setting")
    rates = points.select("setting", "score", *[F.try_divide(F.sum(c).over(run), F.sum(c).over(whole)).alias(c) for c in counts])
    value = {t: F.round(_value(F.col(f"{t}_pos"), F.coalesce(f"{t}_neg", F.lit(0.0)), 0.5, objective), 12) for t in task_names}
    pick = lambda t: F.max_by(F.struct(F.col("score").alias("threshold"), value[t].alias("value")), F.struct(F.coalesce(value[t], F.lit(-1.0)), -F.col("score")))
    best = rates.groupBy("setting").agg(*[pick(t).alias(f"best_{t}") for t in task_names])
    test = long.where("half = 'test'").join(best, "setting", "right")
    share = lambda tuned, c: F.try_divide(F.count_if(F.col(c) & (F.col("score") <= F.col(f"best_{tuned}.threshold"))), F.count_if(c))
    pairs = list(itertools.product(task_names, task_names))
    tested = test.groupBy("setting", *[f"best_{t}" for t in task_names]).agg(*[share(a, f"{b}_{k}").alias(f"{a}_{b}_{k}") for a, b in pairs for k in ("pos", "neg")])
    cells = F.array(*[F.struct(F.lit(a).alias("tuned_on"), F.lit(b).alias("tested_on"), F.col(f"best_{a}.threshold").alias("threshold"), F.col(f"best_{a}.value").alias("tune_value"), F.round(_value(F.col(f"{a}_{b}_pos"), F.coalesce(f"{a}_{b}_neg", F.lit(0.0)), 0.5, "f1"), 12).alias("test_f1")) for a, b in pairs])
    out = tested.select("setting", F.inline(cells))
    return out.join(F.broadcast(settings_table(docs.sparkSession, settings)), "setting").drop("setting")


def top_settings(results: DataFrame, k: int = 10, by: Sequence[str] = ("tuned_on", "metric")) -> DataFrame:
    """The ``k`` settings of each group with the best tune value; of equal ones, by signature."""
    own = results.where("tuned_on = tested_on").select(*by, "signature", "tune_value")
    w = Window.partitionBy(*by).orderBy(F.desc("tune_value"), "signature")
    return own.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def tune_test_matrix(results: DataFrame, k: int = 10) -> DataFrame:
    """Mean test F1 and its 95% interval over the ``k`` best tune settings, for each metric, task tuned on and task tested on."""
    best = top_settings(results, k).select("tuned_on", "metric", "signature")
    rows = results.join(F.broadcast(best), ["tuned_on", "metric", "signature"])
    return ms.mean_with_interval(rows, "test_f1", "metric", "tuned_on", "tested_on")


def relative_gains(results: DataFrame, k: int = 10) -> DataFrame:
    """``tuned_on, metric, tune_f1, test_f1, tune_gain, test_gain``: means over the ``k`` best tune settings of each metric, and by how much each exceeds that of the distinct share."""
    gap = generalisation_gap(results, k).drop("gap")
    base = gap.where("metric = 'ttr'").select("tuned_on", F.col("tune_f1").alias("b_tune"), F.col("test_f1").alias("b_test"))
    gain = lambda a, b: F.try_divide(F.col(a), F.col(b)) - 1
    return gap.join(F.broadcast(base), "tuned_on").select("tuned_on", "metric", "tune_f1", "test_f1", gain("tune_f1", "b_tune").alias("tune_gain"), gain("test_f1", "b_test").alias("test_gain"))


def best_setting_per_n(results: DataFrame) -> DataFrame:
    """The best setting of each task, metric and n-gram length or mix of them."""
    own = results.where("tuned_on = tested_on")
    w = Window.partitionBy("tuned_on", "metric", "unit", "lengths").orderBy(F.desc("tune_value"), "signature")
    return own.withColumn("place", F.row_number().over(w)).where("place = 1").select("tuned_on", "metric", "unit", "n", "lengths", "signature", "threshold", "tune_value", "test_f1")


def parameter_effect(results: DataFrame, parameters: Sequence[str] = ("n", "lengths", "lam", "eps", "top_k", "g", "d", "asymptote")) -> DataFrame:
    """Best and mean test F1 with one parameter held at each of its values."""
    own = results.where("tuned_on = tested_on")
    pairs = F.explode(F.array(*[F.struct(F.lit(p).alias("parameter"), F.coalesce(F.col(p).cast("string"), F.lit({"top_k": "inf", "asymptote": "inf", "n": "several"}.get(p, "none"))).alias("value")) for p in parameters]))
    return own.select("tuned_on", "metric", "test_f1", pairs.alias("x")).groupBy("tuned_on", "metric", "x.parameter", "x.value").agg(F.count(F.lit(1)).alias("n_settings"), F.max("test_f1").alias("best_f1"), F.avg("test_f1").alias("mean_f1"))


def generalisation_gap(results: DataFrame, k: int = 10) -> DataFrame:
    """How far test F1 falls below tune F1 for the ``k`` best settings of each metric."""
    best = top_settings(results, k).select("tuned_on", "metric", "signature")
    rows = results.where("tuned_on = tested_on").join(F.broadcast(best), ["tuned_on", "metric", "signature"])
    return rows.groupBy("tuned_on", "metric").agg(F.avg("tune_value").alias("tune_f1"), F.avg("test_f1").alias("test_f1"), F.avg(F.col("tune_value") - F.col("test_f1")).alias("gap"))
