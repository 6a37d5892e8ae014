"""The experiments as queries over the given tables, and the same in DuckDB's SQL."""

from __future__ import annotations

import functools
import math
import os
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textredun.functions import sql as sql_functions
from textredun.functions.signature import Ensemble, Setting, parse_signature, signature
from textredun.operators import corpus, measures, metrics, tasks, tuning
from textredun.operators import spectrum as sp
from textredun.sources import documents as src
from textredun.sources import sinks
from textredun.sources.shared import fresh_path
from textredun.streaming import scoring as streaming

TTR6, MOMENT6, ZIPF4 = Setting(metric="ttr"), Setting(), Setting(metric="zipf", n=4)
NUDGE = 1e-10
RELEASED = [TTR6, MOMENT6, ZIPF4, MOMENT6.but(k=1.5), MOMENT6.but(k=3.0), MOMENT6.but(g="sq_entropy"), ZIPF4.but(d="log", norm="difference"), ZIPF4.but(d="jsd"), MOMENT6.but(n=5), ZIPF4.but(n=5), Setting(unit="token", n=1), Setting(metric="ttr", unit="token", n=1), Ensemble((MOMENT6, MOMENT6.but(n=5)))]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``doc_id, text`` of all documents, over all cores."""
    return src.spread(table(spark, sf_dir, "documents").select("doc_id", "text"))


def rounded(df: DataFrame, *names: str) -> DataFrame:
    """Columns at six places. The nudge settles halves, which the last bit of a sum would else decide, and clears signed zeros."""
    return df.withColumns({n: F.round(F.col(n) + NUDGE, 6) for n in names})


def one_score(s: Setting, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's score under one setting, over its whole text."""
    return rounded(metrics.score_documents(texts(spark, sf_dir), s).select("doc_id", "n_total", "score"), "score")


def many_scores(settings: list[Setting], spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's scores under several settings, from one count."""
    return rounded(metrics.score_documents(texts(spark, sf_dir), settings).select("doc_id", "signature", "score"), "score")


# --- SQL pieces --------------------------------------------------------------------------------------


def prof_sql(unit: str = "char", n: int = 6, docs: str = "SELECT doc_id, text FROM documents", tag: str = "", cap: int | None = None) -> str:
    """CTEs docs, prof (doc_id, c per n-gram) and tot (doc_id, n_total, n_types)."""
    text = "text" if cap is None else f"substr(text, 1, {cap})"
    if unit == "char":  # in stretches, as DuckDB finds a substring from the start of its string
        return f"""docs{tag} AS (SELECT doc_id, {text} AS t FROM ({docs})),
prof{tag} AS (SELECT doc_id, g, count(*)::DOUBLE AS c FROM (
  SELECT doc_id, substr(t, i, {n}) AS g FROM (SELECT doc_id, substr(t, s + 1, {511 + n}) AS t FROM docs{tag}, unnest(range(0, length(t)::BIGINT - {n} + 1, 512)) AS w(s)), unnest(range(1, length(t)::BIGINT - {n} + 2)) AS u(i)) GROUP BY doc_id, g),
tot{tag} AS (SELECT doc_id, sum(c)::BIGINT AS n_total, count(*)::BIGINT AS n_types FROM prof{tag} GROUP BY doc_id)"""
    if unit == "line":
        units, size, gram = f"string_split(coalesce({text}, ''), chr(10)) AS t", "len(t)", f"array_to_string(t[i:i + {n - 1}], chr(10))"
    else:
        units, size, gram = f"list_filter(regexp_split_to_array({text}, '\\s+'), lambda x: x <> '') AS t", "len(t)", f"array_to_string(t[i:i + {n - 1}], ' ')"
    return f"""docs{tag} AS (SELECT doc_id, {units} FROM ({docs})),
prof{tag} AS (SELECT doc_id, g, count(*)::DOUBLE AS c FROM (
  SELECT doc_id, {gram} AS g FROM docs{tag}, unnest(range(1, {size}::BIGINT - {n} + 2)) AS u(i)) GROUP BY doc_id, g),
tot{tag} AS (SELECT doc_id, sum(c)::BIGINT AS n_total, count(*)::BIGINT AS n_types FROM prof{tag} GROUP BY doc_id)"""


def length_sql(s: Setting) -> str:
    if math.isinf(s.asymptote):
        return "n_total::DOUBLE"
    return {"clamp": f"least(n_total::DOUBLE, {s.asymptote})", "hyperbolic": f"(n_total * {s.asymptote} / (n_total + {s.asymptote}))", "exponential": f"({s.asymptote} * (1 - exp(-n_total / {s.asymptote})))"}[s.mode]


def kept_sql(s: Setting, tag: str = "") -> str:
    """A query doc_id, c, r of the n-grams that clipping leaves, r counting from the most frequent one."""
    over = f"c > {s.eps}" if s.eps_on == "count" else f"c > {s.eps} * n_total"
    ranked = f"SELECT doc_id, c, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC) AS r FROM prof{tag} JOIN tot{tag} USING (doc_id) WHERE {over}"
    return f"SELECT * FROM ({ranked}) WHERE r <= {s.top_k}" if s.top_k else ranked


def moment_sql(s: Setting, tag: str = "") -> str:
    """A query doc_id, n_total, score over prof and tot."""
    form = {"pow": f"power(p, {s.k})", "entropy": "-p * ln(p)", "sq_entropy": "power(p * ln(p), 2)"}[s.g]
    ref = {"pow": f"power(m, {1 - s.k})", "entropy": "ln(m)", "sq_entropy": "power(ln(m), 2) / m"}[s.g]
    share = f"SELECT doc_id, (c + {s.lam}) / sum(c + {s.lam}) OVER (PARTITION BY doc_id) AS p FROM ({kept_sql(s, tag)})"
    raw = f"SELECT doc_id, sum({form}) AS raw FROM ({share}) GROUP BY doc_id"
    ratio = f"raw / nullif({ref}, 0)"
    score = "raw" if s.norm == "none" else f"raw - {ref}" if s.norm == "difference" else f"1 - {ratio}" if s.g == "entropy" else ratio
    return f"""SELECT doc_id, n_total, {score} AS score
FROM (SELECT doc_id, n_total, coalesce(raw, 0) AS raw, {length_sql(s)} AS m FROM tot{tag} LEFT JOIN ({raw}) USING (doc_id))"""


def ttr_sql(s: Setting, tag: str = "") -> str:
    kept = f"SELECT doc_id, 1 - count(*) / sum(c + {s.lam}) AS score FROM ({kept_sql(s, tag)}) GROUP BY doc_id"
    return f"SELECT doc_id, n_total, coalesce(score, 0) AS score FROM tot{tag} LEFT JOIN ({kept}) USING (doc_id)"


DISTANCE_SQL = {
    "sq": "power(q - p, 2)",
    "abs": "abs(q - p)",
    "log": "ln(greatest(abs(q - p), 1e-12))",
    "sq_log": "power(ln(greatest(abs(q - p), 1e-12)), 2)",
    "jsd": "0.5 * (p * ln(p / ((p + q) / 2)) + q * ln(q / ((p + q) / 2)))",
    "kl_pq": "p * ln(p / q)",
    "kl_qp": "q * ln(q / p)",
}


def zipf_sql(s: Setting, tag: str = "", shares: str | None = None) -> str:
    """A query doc_id, n_total, score over prof and tot. ``shares``: a query rank, w in place of 1 / rank."""
    power = f"(1.0 / power(r + {s.shift}, {s.exponent}))"
    w = "coalesce(w, 0)" if shares else power
    source = f"LEFT JOIN ({shares}) sh ON sh.rank = r" if shares else ""
    form = DISTANCE_SQL[s.d]
    ranks = f"SELECT doc_id, c / sum(c) OVER (PARTITION BY doc_id) AS p, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC) AS r FROM prof{tag}"
    if s.support == "bounded":
        ranks += f" UNION ALL SELECT doc_id, 0.0::DOUBLE, unnest(range(n_types + 1, greatest(n_types, floor({length_sql(s)})::BIGINT) + 1)) FROM tot{tag}"
    raw = f"""SELECT doc_id, sum({form}) AS raw FROM (
    SELECT doc_id, p, {w} / sum({w}) OVER (PARTITION BY doc_id) AS q FROM ({ranks}) {source}) GROUP BY doc_id"""
    ref = f"""SELECT m, sum({form}) AS ref FROM (
    SELECT m, 1.0 / m AS p, {w} / sum({w}) OVER (PARTITION BY m) AS q FROM (
      SELECT m, unnest(range(1, floor(m)::BIGINT + 1)) AS r FROM (SELECT DISTINCT {length_sql(s)} AS m FROM tot{tag})) {source}) GROUP BY m"""
    score = {"ratio": "CASE WHEN abs(ref) > 1e-12 THEN raw / ref END", "difference": "raw - ref", "none": "raw"}[s.norm]
    return f"""SELECT doc_id, n_total, {score} AS score
FROM (SELECT *, {length_sql(s)} AS m FROM tot{tag}) JOIN ({raw}) USING (doc_id) JOIN ({ref}) USING (m)"""


def score_query_sql(s: Setting, tag: str = "") -> str:
    return {"ttr": ttr_sql, "moment": moment_sql, "zipf": zipf_sql}[s.metric](s, tag)


def all_docs_sql(score: str, docs: str = "documents") -> str:
    return f"SELECT d.doc_id, coalesce(n_total, 0)::BIGINT AS n_total, round(score + 1e-10, 6) AS score FROM {docs} d LEFT JOIN ({score}) USING (doc_id)"


def one_score_sql(s: Setting) -> str:
    return f"WITH {prof_sql(s.unit, s.n)}\n{all_docs_sql(score_query_sql(s))}"


def many_scores_sql(settings: list[Setting]) -> str:
    specs = sorted({s.spec for s in settings})
    ctes = ",\n".join(prof_sql(u, n, tag=f"_{u}{n}") for u, n in specs)
    parts = [f"SELECT d.doc_id, '{signature(s)}' AS signature, round(score + 1e-10, 6) AS score FROM documents d LEFT JOIN ({score_query_sql(s, f'_{s.unit}{s.n}')}) USING (doc_id)" for s in settings]
    return f"WITH {ctes}\n" + "\nUNION ALL\n".join(parts)


CLASSES_SQL = """labelled AS (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY doc_id),
worded AS (SELECT doc_id, text, lang, list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '') AS w FROM documents),
classes AS (SELECT doc_id, text, lang,
  CASE WHEN quality = 1 THEN 'natural' WHEN quality IS NULL THEN 'unsure'
       WHEN coalesce(list_sum(list_transform(range(1, len(w)), lambda i: (w[i] = w[i + 1])::INTEGER)), 0)::DOUBLE / nullif(len(w), 0) > 0.3 THEN 'repetitive'
       ELSE 'noise' END AS label_class,
  CASE WHEN ('0x' || substr(md5(text), 1, 8))::BIGINT % 2 = 0 THEN 'tune' ELSE 'test' END AS half
  FROM worded LEFT JOIN labelled USING (doc_id))"""
SURE = "SELECT doc_id, text FROM classes WHERE label_class <> 'unsure'"


def classes_of(spark, sf_dir, unsure=True):
    return tasks.classified(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), unsure=unsure)


# --- distributions and classes -------------------------------------------------------------------------


def toy_histogram(spark, sf_dir):
    """The ten most frequent 6-grams of the most and the least repetitive document."""
    s = one_score(MOMENT6, spark, sf_dir).where("score IS NOT NULL").select("doc_id", "score")
    worst = s.orderBy(F.desc("score"), "doc_id").limit(1).withColumn("kind", F.lit("most repetitive"))
    best = s.orderBy("score", "doc_id").limit(1).withColumn("kind", F.lit("least repetitive"))
    two = F.broadcast(worst.unionByName(best).select("doc_id", "kind"))
    docs = table(spark, sf_dir, "documents").join(two, "doc_id", "left_semi")
    return sp.gram_histogram(docs, top=10).join(two, "doc_id").select("kind", "doc_id", "gram", "cnt", F.col("rank").cast("bigint").alias("rank"))


TOY_SQL = f"""WITH {prof_sql()}, s AS (SELECT doc_id, round(score + 1e-10, 6) AS score FROM ({moment_sql(MOMENT6)})),
two AS ((SELECT doc_id, 'most repetitive' AS kind FROM s ORDER BY score DESC, doc_id LIMIT 1) UNION ALL (SELECT doc_id, 'least repetitive' FROM s ORDER BY score, doc_id LIMIT 1))
SELECT kind, doc_id, g AS gram, c::BIGINT AS cnt, rank FROM (
  SELECT kind, doc_id, g, c, row_number() OVER (PARTITION BY doc_id, kind ORDER BY c DESC, g) AS rank FROM prof JOIN two USING (doc_id)) WHERE rank <= 10"""


def corpus_histogram(spark, sf_dir):
    """The ten most frequent 3-grams of each language's texts taken together."""
    counts = sp.pooled_counts(table(spark, sf_dir, "documents"), "char", 3, "lang")
    return sp.corpus_histogram(counts, 10).select(F.col("doc_id").alias("lang"), "gram", "cnt", F.col("rank").cast("bigint").alias("rank"))


POOLED_SQL = "SELECT lang, g, count(*) AS c FROM (SELECT lang, substr(text, i, 3) AS g FROM (SELECT lang, substr(text, s + 1, 514) AS text FROM documents, unnest(range(0, length(text)::BIGINT - 2, 512)) AS w(s)), unnest(range(1, length(text)::BIGINT - 1)) AS u(i)) GROUP BY lang, g"
CORPUS_HISTOGRAM_SQL = f"SELECT lang, g AS gram, c AS cnt, rank FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY c DESC, g) AS rank FROM ({POOLED_SQL})) WHERE rank <= 10"


def pooled_moment(spark, sf_dir):
    """Size, vocabulary and second moment of each language's 3-grams, all texts taken together."""
    x = sp.pooled_spectra(sp.pooled_counts(table(spark, sf_dir, "documents"), "char", 3, "lang"), "char", 3)
    x = metrics.native_score(x, Setting(n=3, norm="none"), name="moment")
    return x.select(F.col("doc_id").alias("lang"), "n_total", "n_types", F.round(F.col("moment") + NUDGE, 9).alias("moment"))


POOLED_MOMENT_SQL = f"SELECT lang, sum(c)::BIGINT AS n_total, count(*) AS n_types, round(sum(power(c / t, 2)) + 1e-10, 9) AS moment FROM (SELECT *, sum(c) OVER (PARTITION BY lang) AS t FROM ({POOLED_SQL})) GROUP BY lang"


def class_counts(spark, sf_dir):
    """Documents of each class."""
    return classes_of(spark, sf_dir).groupBy("label_class").agg(F.count(F.lit(1)).alias("n_docs"))


def split_balance(spark, sf_dir):
    """Documents of each class in each half."""
    return classes_of(spark, sf_dir).groupBy("label_class", "half").agg(F.count(F.lit(1)).alias("n_docs"))


def language_cover(spark, sf_dir):
    """Natural documents of each language, and how many a sample of six keeps."""
    c = classes_of(spark, sf_dir, unsure=False)
    kept = tasks.per_language_sample(c).groupBy("lang").agg(F.count(F.lit(1)).alias("n_sampled"))
    return c.where("label_class = 'natural'").groupBy("lang").agg(F.count(F.lit(1)).alias("n_natural")).join(F.broadcast(kept), "lang")


def profile_char6(spark, sf_dir):
    """6-grams, distinct ones and distinct counts of every document."""
    x = sp.spectra(texts(spark, sf_dir), [("char", 6)])
    return x.select("doc_id", "n_total", "n_types", F.size("spectrum").cast("bigint").alias("n_levels"), F.round(F.try_divide("n_types", "n_total") + NUDGE, 6).alias("distinct_share"))


PROFILE_SQL = f"""WITH {prof_sql()} SELECT d.doc_id, coalesce(n_total, 0)::BIGINT AS n_total, coalesce(n_types, 0)::BIGINT AS n_types,
  coalesce(n_levels, 0)::BIGINT AS n_levels, round(n_types::DOUBLE / n_total + 1e-10, 6) AS distinct_share
FROM documents d LEFT JOIN tot USING (doc_id) LEFT JOIN (SELECT doc_id, count(DISTINCT c) AS n_levels FROM prof GROUP BY doc_id) USING (doc_id)"""


def strategy_twin(strategy, spark, sf_dir):
    """Spectra of character 3-grams by one of the other counting strategies."""
    x = sp.spectra(table(spark, sf_dir, "documents"), [("char", 3)], strategy)
    return metrics.native_score(x, Setting(n=3)).select("doc_id", "n_total", "n_types", F.round(F.col("score") + NUDGE, 6).alias("score"))


TWIN_SQL = f"""WITH {prof_sql(n=3)} SELECT d.doc_id, coalesce(t.n_total, 0)::BIGINT AS n_total, coalesce(n_types, 0)::BIGINT AS n_types, round(score + 1e-10, 6) AS score
FROM documents d LEFT JOIN tot t USING (doc_id) LEFT JOIN ({moment_sql(Setting(n=3))}) s USING (doc_id)"""


def own_nonlinearity(spark, sf_dir):
    """A moment under a function of one's own: x to the power 1.2."""
    x = metrics.native_score(sp.spectra(texts(spark, sf_dir), [("char", 6)]), MOMENT6, g=lambda p: F.pow(p, F.lit(1.2)))
    return x.select("doc_id", F.round(F.col("score") + NUDGE, 6).alias("score"))


def window_ttr(spark, sf_dir):
    """Mean share of distinct words over windows of 50 that move word by word, of every document."""
    return rounded(sp.window_ttr(texts(spark, sf_dir), width=50, stride=1), "score")


WINDOW_SQL = """WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '') AS t FROM documents),
x AS (SELECT doc_id, t[s + 1:s + 50] AS u FROM w, unnest(range(0, greatest(len(t) - 50, 0)::BIGINT + 1)) AS r(s) WHERE len(t) > 0)
SELECT d.doc_id, coalesce(n_windows, 0)::BIGINT AS n_windows, round(score + 1e-10, 6) AS score FROM documents d LEFT JOIN (
  SELECT doc_id, count(*) AS n_windows, avg(len(list_distinct(u))::DOUBLE / len(u)) AS score FROM x GROUP BY doc_id) USING (doc_id)"""


def window_ttr_steps(spark, sf_dir):
    """The same with windows side by side, and a last one that ends where the text does."""
    return rounded(sp.window_ttr(texts(spark, sf_dir), width=50, stride=50), "score")


WINDOW_STEPS_SQL = WINDOW_SQL.replace("unnest(range(0, greatest(len(t) - 50, 0)::BIGINT + 1)) AS r(s)", "unnest(list_distinct(list_append(range(0, greatest(len(t) - 50, 0)::BIGINT + 1, 50), greatest(len(t) - 50, 0)::BIGINT))) AS r(s)")


def ttr_capped(spark, sf_dir):
    """1 - V/N of the first 500 6-grams of every document."""
    return rounded(metrics.capped_ttr(table(spark, sf_dir, "documents"), 6, 500), "score")


def zipf_empirical(spark, sf_dir):
    """Squared distance from the mean ranks of natural English documents instead of 1 / rank."""
    docs = table(spark, sf_dir, "documents")
    # counted before the join, so that spectra move and not texts
    counted = sp.spectra(docs.where("lang = 'en'"), [("char", 4)])
    models = metrics.empirical_models(counted.join(table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi"))
    return rounded(metrics.score_documents(texts(spark, sf_dir), ZIPF4.but(norm="none"), models).select("doc_id", "n_total", "score"), "score")


ZIPF_EMPIRICAL_SQL = f"""WITH {prof_sql(n=4)}, clean AS (SELECT doc_id FROM documents WHERE lang = 'en' AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)),
ranked AS (SELECT doc_id, c / sum(c) OVER (PARTITION BY doc_id) AS p, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC) AS r FROM prof),
shares AS (SELECT r AS rank, sum(p) / (SELECT count(*) FROM clean JOIN tot USING (doc_id)) AS w FROM ranked WHERE doc_id IN (SELECT doc_id FROM clean) GROUP BY r)
{all_docs_sql(zipf_sql(ZIPF4.but(norm="none"), shares="SELECT rank, w FROM shares"))}"""


def rank_model_fit(spark, sf_dir):
    """Shape of the mean rank shares of benchmark passages and of natural documents, for 4-grams."""
    clean = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi")
    passages = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
    parts = [metrics.fit_rank_model(sp.spectra(d, [("char", 4)])).withColumn("sample", F.lit(name)) for name, d in (("natural", clean), ("benchmark", passages))]
    return rounded(parts[0].unionByName(parts[1]).select("sample", "n", "n_ranks", "exponent", "intercept", "r2"), "exponent", "intercept", "r2")


def _fit_sql(name: str, tag: str) -> str:
    return f"""SELECT '{name}' AS sample, 4 AS n, count(*)::BIGINT AS n_ranks, round(-regr_slope(ln(w), ln(r)) + 1e-10, 6) AS exponent, round(regr_intercept(ln(w), ln(r)) + 1e-10, 6) AS intercept, round(regr_r2(ln(w), ln(r)) + 1e-10, 6) AS r2
FROM (SELECT r, sum(p) / (SELECT count(*) FROM tot{tag}) AS w FROM (
  SELECT c / sum(c) OVER (PARTITION BY doc_id) AS p, row_number() OVER (PARTITION BY doc_id ORDER BY c DESC) AS r FROM prof{tag}) GROUP BY r)"""


FIT_SQL = f"""WITH {prof_sql(n=4, docs="SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)", tag="_a")},
{prof_sql(n=4, docs="SELECT item_id AS doc_id, text FROM benchmark", tag="_b")}
{_fit_sql("natural", "_a")} UNION ALL {_fit_sql("benchmark", "_b")}"""

MIXED = [MOMENT6, MOMENT6.but(n=5), Setting(unit="token", n=1)]


def ensemble_char_token(spark, sf_dir):
    """Mean of character and word scores."""
    x = metrics.score_documents(texts(spark, sf_dir), Ensemble(tuple(MIXED)))
    return rounded(x.where("valid").select("doc_id", "score"), "score")


ENSEMBLE_SQL = f"""SELECT doc_id, round(avg(score) + 1e-10, 6) AS score FROM (
{many_scores_sql(MIXED).replace("round(score + 1e-10, 6) AS score", "score")}) WHERE score IS NOT NULL GROUP BY doc_id"""


def ensemble_standardised(spark, sf_dir):
    """The same with each score first put in standard deviations from the mean of its setting."""
    s = metrics.score_documents(texts(spark, sf_dir), MIXED)
    return rounded(metrics.ensemble(s, "standardised", metrics.score_stats(s)), "score")


STANDARDISED_SQL = f"""WITH x AS ({many_scores_sql(MIXED).replace("round(score + 1e-10, 6) AS score", "score")}),
z AS (SELECT doc_id, (score - avg(score) OVER (PARTITION BY signature)) / stddev_samp(score) OVER (PARTITION BY signature) AS z FROM x WHERE score IS NOT NULL)
SELECT doc_id, count(z) AS n_scores, round(avg(z) + 1e-10, 6) AS score FROM z GROUP BY doc_id"""


# --- tuning and testing --------------------------------------------------------------------------------

SMALL_GRID = [TTR6, MOMENT6, MOMENT6.but(asymptote=500.0), MOMENT6.but(k=3.0)]
TUNED = ("signature", "threshold", "tune_value", "test_f1")


def small_grid(task, spark, sf_dir, cap=None):
    """Thresholds tuned on one half and F1 on the other, for a few settings."""
    r = tuning.grid_results(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), [s.but(cap=cap) for s in SMALL_GRID], [task], cap=cap)
    return rounded(r.select(*TUNED), *TUNED[1:])


def _negatives(spark, sf_dir):
    """Price lists and log files: texts that are repetitive by what they are."""
    return src.catalogue_docs(table(spark, sf_dir, "part")).select("text").unionByName(src.event_log_docs(table(spark, sf_dir, "events")).select("text"))


def grid_repeat_plus(spark, sf_dir):
    """The repetition task with price lists and log files among the repetitive texts."""
    r = tuning.grid_results(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), SMALL_GRID, ["repeat"], extra=_negatives(spark, sf_dir))
    return rounded(r.select(*TUNED), *TUNED[1:])


def _graded_sql(task: str, settings=SMALL_GRID, cap: int | None = None, extra: str = "") -> str:
    """CTEs up to graded: doc_id, signature, score, half, good of a task's documents; all settings share unit and length."""
    names = ", ".join(f"'{c}'" for c in tasks.TASKS[task])
    scores = "\nUNION ALL\n".join(f"SELECT doc_id, '{signature(s.but(cap=cap))}' AS signature, round(score + 1e-10, 6) AS score FROM ({score_query_sql(s)}) WHERE score IS NOT NULL" for s in settings)
    more = f" UNION ALL SELECT 'x' || row_number() OVER (), text, 'repetitive', CASE WHEN ('0x' || substr(md5(text), 1, 8))::BIGINT % 2 = 0 THEN 'tune' ELSE 'test' END FROM ({extra})" if extra else ""
    return f"""{CLASSES_SQL}, sure AS (SELECT doc_id::VARCHAR AS doc_id, text, label_class, half FROM classes WHERE label_class IN ({names}){more}),
{prof_sql(settings[0].unit, settings[0].n, "SELECT doc_id, text FROM sure", cap=cap)}, scores AS ({scores}),
graded AS (SELECT doc_id, signature, score, half, label_class = 'natural' AS good FROM scores JOIN sure USING (doc_id))"""


def _value_sql(share: float, objective: str) -> str:
    tp, fp, fn, tn = f"({share} * recall)", f"({1 - share} * alarms)", f"({share} - {share} * recall)", f"({1 - share} - {1 - share} * alarms)"
    if objective == "f1":
        return f"round(2 * {tp} / nullif(2 * {tp} + {fp} + {fn}, 0), 12)"
    return f"round(4 * {tp} * {tn} / nullif(4 * {tp} * {tn} + ({tp} + {tn}) * ({fp} + {fn}), 0), 12)"


def _rates_sql(source: str, by: str = "signature") -> str:
    """A query *by, threshold, recall, alarms: shares of both classes that pass at each distinct score."""
    return f"""SELECT {by}, score AS threshold, sum(g) OVER run / nullif(sum(g) OVER whole, 0) AS recall, coalesce(sum(b) OVER run / nullif(sum(b) OVER whole, 0), 0) AS alarms FROM (
    SELECT {by}, score, count(*) FILTER (good)::DOUBLE AS g, count(*) FILTER (NOT good)::DOUBLE AS b FROM ({source}) GROUP BY {by}, score)
  WINDOW run AS (PARTITION BY {by} ORDER BY score ROWS UNBOUNDED PRECEDING), whole AS (PARTITION BY {by})"""


def _tuned_sql(source: str, share: float = 0.5, objective: str = "f1", by: str = "signature") -> str:
    """A query *by, threshold, value: the lowest of the best thresholds."""
    return f"""SELECT {by}, threshold, value FROM (SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY coalesce(value, -1) DESC, threshold) AS place FROM (
  SELECT *, {_value_sql(share, objective)} AS value FROM ({_rates_sql(source, by)}))) WHERE place = 1"""


def small_grid_sql(task: str, cap: int | None = None, extra: str = "") -> str:
    return f"""WITH {_graded_sql(task, cap=cap, extra=extra)}, best AS ({_tuned_sql("SELECT * FROM graded WHERE half = 'tune'")}),
said AS (SELECT signature, threshold, value, count(*) FILTER (good AND score <= threshold)::DOUBLE / nullif(count(*) FILTER (good), 0) AS recall,
  coalesce(count(*) FILTER (NOT good AND score <= threshold)::DOUBLE / nullif(count(*) FILTER (NOT good), 0), 0) AS alarms
  FROM best LEFT JOIN (SELECT * FROM graded WHERE half = 'test') USING (signature) GROUP BY ALL)
SELECT signature, round(threshold + 1e-10, 6) AS threshold, round(value + 1e-10, 6) AS tune_value, round({_value_sql(0.5, "f1")} + 1e-10, 6) AS test_f1 FROM said"""


def threshold_curve(spark, sf_dir):
    """F1 and P4 at every threshold of the moment score, on the noise task."""
    scored = metrics.with_scores(classes_of(spark, sf_dir, unsure=False), {"score": MOMENT6}).drop("text").withColumn("score", tuning.rounded_score("score"))
    rows = scored.where(F.col("label_class").isin(*tasks.TASKS["noise"])).where("half = 'tune'").select(F.lit(signature(MOMENT6)).alias("signature"), "score", (F.col("label_class") == "natural").alias("is_natural"))
    return rounded(tuning.rates(rows).select(F.col("score").alias("threshold"), *[tuning.point_value(0.5, k).alias(k) for k in ("f1", "p4")]), "threshold", "f1", "p4")


CURVE_SQL = f"""WITH {_graded_sql("noise", [MOMENT6])}
SELECT round(threshold + 1e-10, 6) AS threshold, round({_value_sql(0.5, "f1")} + 1e-10, 6) AS f1, round({_value_sql(0.5, "p4")} + 1e-10, 6) AS p4 FROM ({_rates_sql("SELECT * FROM graded WHERE half = 'tune'")})"""


def constant_baseline(spark, sf_dir):
    """Calling every document natural: the floor of each task, without weights."""
    c = classes_of(spark, sf_dir, unsure=False).select("label_class", "half")
    parts = [tuning.constant_baseline(tasks.task(c, t, balanced=False)).withColumn("task", F.lit(t)) for t in tasks.TASKS]
    return rounded(parts[0].unionByName(parts[1]).select("task", "tp", "fp", "precision", "recall", "f1"), "precision", "recall", "f1")


CONSTANT_SQL = f"""WITH {CLASSES_SQL}, t AS (
  SELECT 'repeat' AS task, label_class FROM classes WHERE label_class IN ('natural', 'repetitive') UNION ALL SELECT 'noise', label_class FROM classes WHERE label_class <> 'unsure')
SELECT task, tp, fp, round(tp / (tp + fp) + 1e-10, 6) AS precision, 1.0::DOUBLE AS recall, round(2 * tp / (2 * tp + fp) + 1e-10, 6) AS f1 FROM (
  SELECT task, sum((label_class = 'natural')::INTEGER)::DOUBLE AS tp, sum((label_class <> 'natural')::INTEGER)::DOUBLE AS fp FROM t GROUP BY task)"""

THREE = {"ttr": TTR6, "moment": MOMENT6, "zipf": ZIPF4}


def _learned(spark, sf_dir, settings=THREE):
    return tuning.learned_thresholds(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), settings)


def operating_points(spark, sf_dir):
    """The released thresholds of each classifier, from the tune half: best F1 with equal classes, best P4 with three quarters natural."""
    return rounded(_learned(spark, sf_dir), "threshold", "value")


def boundary(spark, sf_dir, settings=None, point="balanced_f1"):
    """The learned decision boundary of the moment score: one row ``threshold``."""
    return _learned(spark, sf_dir, settings or {"moment": MOMENT6}).where(F.col("operating_point") == point).select("threshold")


def _points_ctes(settings: dict[str, Setting]) -> str:
    """CTEs up to points: name, operating_point, threshold, value."""
    specs = sorted({s.spec for s in settings.values()})
    profs = ",\n".join(prof_sql(u, n, SURE, f"_p{u}{n}") for u, n in specs)
    scores = " UNION ALL ".join(f"SELECT '{k}' AS name, doc_id, round(score + 1e-10, 6) AS score FROM ({score_query_sql(s, f'_p{s.unit}{s.n}')}) WHERE score IS NOT NULL" for k, s in settings.items())
    half = "SELECT name, score, good FROM base"
    cases = " UNION ALL ".join(f"SELECT name, '{k}' AS operating_point, threshold, value FROM ({_tuned_sql(half, share, objective, 'name')})" for k, (share, objective) in tuning.OPERATING_POINTS.items())
    return f"""{CLASSES_SQL},
{profs},
base AS (SELECT name, score, label_class = 'natural' AS good FROM ({scores}) JOIN classes USING (doc_id) WHERE label_class <> 'unsure' AND half = 'tune'),
points AS ({cases})"""


POINTS_SQL = f"WITH {_points_ctes(THREE)} SELECT name, operating_point, round(threshold + 1e-10, 6) AS threshold, round(value + 1e-10, 6) AS value FROM points"
MOMENT_CTES = f"""{_points_ctes({"moment": MOMENT6})}, line AS (SELECT threshold FROM points WHERE operating_point = 'balanced_f1')"""

# --- grids -----------------------------------------------------------------------------------------------

PLACES = 5
_results: dict[tuple, DataFrame] = {}


def grid(spark, sf_dir, name="final"):
    """Results of a whole grid over both tasks. Written once for each session and data folder; the queries on it share them (``forget_grids`` starts anew)."""
    from textredun.sources.shared import written

    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _results:
        settings = tuning.final_grid() if name == "final" else tuning.deep_grid()
        _results[key] = written(tuning.grid_results(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), settings, places=PLACES), f"grid-{name}")
    return _results[key]


def forget_grids() -> None:
    _results.clear()


GRID_DOUBLES = ("threshold", "tune_value", "test_f1")


def grid_full(spark, sf_dir):
    """Every setting of the restricted grid: tuned on each task, tested on each."""
    return rounded(grid(spark, sf_dir), *GRID_DOUBLES)


def tune_test_matrix(spark, sf_dir):
    """Mean test F1 of the ten best settings, by metric, task tuned on and task tested on."""
    return rounded(tuning.tune_test_matrix(grid(spark, sf_dir)), "mean", "ci95")


def relative_gain(spark, sf_dir):
    """By how much the moment score and the rank distance beat the distinct share on each task."""
    return rounded(tuning.relative_gains(grid(spark, sf_dir)), "tune_f1", "test_f1", "tune_gain", "test_gain")


def best_setting_per_n(spark, sf_dir):
    """The best setting of each n-gram length and mix."""
    return rounded(tuning.best_setting_per_n(grid(spark, sf_dir)), *GRID_DOUBLES)


def parameter_effect(spark, sf_dir):
    """Best and mean F1 with one parameter held."""
    return rounded(tuning.parameter_effect(grid(spark, sf_dir)), "best_f1", "mean_f1")


def grid_overfit(spark, sf_dir):
    """How much more the best settings of the wide grid lose from tune to test than those of the restricted one."""
    parts = [tuning.generalisation_gap(grid(spark, sf_dir, name)).withColumn("grid", F.lit(name)) for name in ("final", "deep")]
    return parts[0].unionByName(parts[1])


def _number_sql(x: str) -> str:
    """SQL for the text of a parameter in a signature."""
    return f"CASE WHEN isinf({x}) THEN 'inf' WHEN {x} = floor({x}) THEN {x}::BIGINT::VARCHAR ELSE {x}::VARCHAR END"


def _grid_ctes() -> str:
    """CTEs up to grid: the rows of the restricted grid, from spectra of the labelled documents."""
    specs = [("char", n) for n in range(1, 9)] + [("token", 1), ("token", 2)]
    profs = ",\n".join(prof_sql(u, n, "SELECT doc_id, text FROM lab", f"_{u}{n}") for u, n in specs)
    every = " UNION ALL ".join(f"SELECT doc_id, '{u}' AS u, {n} AS n, c FROM prof_{u}{n}" for u, n in specs)
    groups = [(f"{u}:{n}", u, n, i) for u, n in specs for i in (0,)] + [(name, u, n, i) for name, of in tuning.MIXES.items() for i, (u, n) in enumerate(of)]
    mem = ", ".join(f"('{g}', '{u}', {n}, {i})" for g, u, n, i in groups)
    tested = " UNION ALL ".join(
        f"""SELECT key, '{a}' AS tuned_on, '{b}' AS tested_on, threshold, value, count(*) FILTER ({b} AND good AND score <= threshold)::DOUBLE / nullif(count(*) FILTER ({b} AND good), 0) AS recall,
  coalesce(count(*) FILTER ({b} AND NOT good AND score <= threshold)::DOUBLE / nullif(count(*) FILTER ({b} AND NOT good), 0), 0) AS alarms FROM best_{a} JOIN long USING (key) WHERE half = 'test' GROUP BY ALL"""
        for a in tasks.TASKS for b in tasks.TASKS
    )
    best = ", ".join(f"""best_{t} AS ({_tuned_sql(f"SELECT * FROM long WHERE half = 'tune' AND {t}", by="key")})""" for t in tasks.TASKS)
    return f"""{CLASSES_SQL}, lab AS MATERIALIZED (SELECT doc_id, text, label_class, half FROM classes WHERE label_class <> 'unsure'),
{profs},
allp AS MATERIALIZED ({every}),
size AS (SELECT doc_id, u, n, sum(c) AS nt, count(*)::DOUBLE AS vt FROM allp GROUP BY ALL),
levels AS (SELECT doc_id, u, n, c, count(*)::DOUBLE AS v FROM allp GROUP BY ALL),
lams AS (SELECT unnest([0.0, 0.1, 1.0]::DOUBLE[]) AS lam),
lens AS (SELECT unnest([500.0, 1000.0, 2000.0, 5000.0, 'infinity'::DOUBLE]::DOUBLE[]) AS a),
mass AS (SELECT doc_id, u, n, lam, sum(v * (c + lam)) AS z FROM levels, lams GROUP BY ALL),
harm AS (SELECT r, 1.0 / r AS w, sum(1.0 / r) OVER (ORDER BY r) AS h FROM (SELECT unnest(range(1, (SELECT max(nt)::BIGINT + 1 FROM size))) AS r)),
kinds AS (SELECT unnest(['pow1.5', 'pow2', 'pow3', 'sq_entropy']) AS kind),
raw AS (
  SELECT doc_id, u, n, lam, 'moment' AS metric, kind, sum(v * CASE kind WHEN 'pow1.5' THEN power(p, 1.5) WHEN 'pow2' THEN power(p, 2.0) WHEN 'pow3' THEN power(p, 3.0) ELSE power(p * ln(p), 2) END) AS raw
  FROM (SELECT *, (c + lam) / z AS p FROM levels JOIN mass USING (doc_id, u, n)), kinds GROUP BY ALL
  UNION ALL
  SELECT doc_id, u, n, lam, 'zipf', kind, CASE kind WHEN 'sq' THEN sq ELSE lg END FROM (
    SELECT doc_id, u, n, lam, sum(power(w / h - p, 2)) AS sq, sum(ln(greatest(abs(w / h - p), 1e-12))) AS lg FROM (
      SELECT doc_id, u, n, lam, w, h, (c + lam) / z AS p FROM (SELECT *, row_number() OVER (PARTITION BY doc_id, u, n ORDER BY c DESC) AS r FROM allp)
      JOIN (SELECT r, w FROM harm) USING (r) JOIN size USING (doc_id, u, n) JOIN (SELECT r::DOUBLE AS vt, h FROM harm) USING (vt) JOIN mass USING (doc_id, u, n)) GROUP BY ALL), (SELECT unnest(['sq', 'log']) AS kind)),
ms AS (SELECT *, least(nt, a) AS m FROM size, lens),
refs AS (SELECT m, sum(power(w / h - 1 / m, 2)) AS sq, sum(ln(greatest(abs(w / h - 1 / m), 1e-12))) AS lg FROM (SELECT DISTINCT m FROM ms) JOIN (SELECT r::DOUBLE AS m, h FROM harm) USING (m) JOIN (SELECT r, w FROM harm) ON r <= m GROUP BY m),
one AS (
  SELECT doc_id, u, n, lam, a, metric, kind, CASE WHEN metric = 'moment' THEN raw / nullif(CASE kind WHEN 'pow1.5' THEN power(m, -0.5) WHEN 'pow2' THEN power(m, -1.0) WHEN 'pow3' THEN power(m, -2.0) ELSE power(ln(m), 2) / m END, 0)
    WHEN kind = 'sq' THEN CASE WHEN abs(sq) > 1e-12 THEN raw / sq END ELSE raw - lg END AS score
  FROM raw JOIN ms USING (doc_id, u, n) JOIN refs USING (m)
  UNION ALL SELECT doc_id, u, n, lam, NULL, 'ttr', NULL, 1 - vt / z FROM size JOIN mass USING (doc_id, u, n)),
mem(lengths, u, n, i) AS (VALUES {mem}),
named AS (SELECT lengths, u, n, i, lam, a, metric, kind,
  metric || '|u=' || u || '|n=' || n || '|lam=' || {_number_sql("lam")} || '|eps=0@count|k=inf' || CASE metric WHEN 'moment' THEN '|g=' || kind WHEN 'zipf' THEN '|d=' || kind || '|q=power:1:0:observed' ELSE '' END
  || CASE WHEN metric = 'ttr' THEN '' ELSE '|A=' || {_number_sql("a")} || ':clamp:' || CASE WHEN kind = 'log' THEN 'difference' ELSE 'ratio' END END || '|cap=inf|v=1' AS sig
  FROM mem, (SELECT DISTINCT lam, a, metric, kind FROM one)),
params AS (SELECT lengths, lam, a, metric, kind, CASE WHEN count(*) = 1 THEN min(sig) ELSE 'mean(' || string_agg(sig, ';' ORDER BY i) || ')' END AS signature,
  CASE WHEN count(DISTINCT u) = 1 THEN min(u) ELSE 'mixed' END AS unit, CASE WHEN count(*) = 1 THEN min(n) END::INTEGER AS n, row_number() OVER () AS key FROM named GROUP BY ALL),
long AS MATERIALIZED (SELECT key, round(avg(score) + 1e-10, {PLACES}) AS score, label_class = 'natural' AS good, half, label_class <> 'noise' AS repeat, true AS noise
  FROM one JOIN mem USING (u, n) JOIN params p ON p.lengths = mem.lengths AND p.lam = one.lam AND p.a IS NOT DISTINCT FROM one.a AND p.metric = one.metric AND p.kind IS NOT DISTINCT FROM one.kind JOIN lab USING (doc_id)
  WHERE score IS NOT NULL GROUP BY key, doc_id, label_class, half),
{best},
tested AS ({tested}),
grid AS (SELECT tuned_on, tested_on, threshold, value AS tune_value, {_value_sql(0.5, "f1")} AS test_f1, signature, metric, unit, n, lengths, lam, 0.0::DOUBLE AS eps, NULL::INTEGER AS top_k,
  CASE WHEN metric = 'moment' THEN CASE WHEN kind LIKE 'pow%' THEN 'pow' ELSE kind END END AS g, CASE WHEN metric = 'moment' AND kind LIKE 'pow%' THEN substr(kind, 4)::DOUBLE END AS k, CASE WHEN metric = 'zipf' THEN kind END AS d, CASE WHEN isinf(a) THEN NULL ELSE a END AS asymptote
  FROM tested JOIN params USING (key))"""


def _round_sql(*names: str) -> str:
    return ", ".join(f"round({n} + 1e-10, 6) AS {n}" for n in names)


GRID_CTES = _grid_ctes()
TOP_SQL = "SELECT tuned_on, metric, signature FROM (SELECT *, row_number() OVER (PARTITION BY tuned_on, metric ORDER BY tune_value DESC, signature) AS place FROM grid WHERE tuned_on = tested_on) WHERE place <= 10"
GRID_SQL = f"WITH {GRID_CTES} SELECT * REPLACE ({_round_sql(*GRID_DOUBLES)}) FROM grid"
MATRIX_SQL = f"""WITH {GRID_CTES} SELECT metric, tuned_on, tested_on, n, {_round_sql("mean", "ci95")} FROM (
  SELECT metric, tuned_on, tested_on, count(test_f1) AS n, avg(test_f1) AS mean, {measures.t_975(9)} * stddev_samp(test_f1) / sqrt(count(test_f1)) AS ci95 FROM grid JOIN ({TOP_SQL}) USING (tuned_on, metric, signature) GROUP BY ALL)"""
GAIN_SQL = f"""WITH {GRID_CTES}, gap AS (SELECT tuned_on, metric, avg(tune_value) AS tune_f1, avg(test_f1) AS test_f1 FROM grid JOIN ({TOP_SQL}) USING (tuned_on, metric, signature) WHERE tuned_on = tested_on GROUP BY ALL)
SELECT g.tuned_on, g.metric, round(g.tune_f1 + 1e-10, 6) AS tune_f1, round(g.test_f1 + 1e-10, 6) AS test_f1, round(g.tune_f1 / b.tune_f1 - 1 + 1e-10, 6) AS tune_gain, round(g.test_f1 / b.test_f1 - 1 + 1e-10, 6) AS test_gain
FROM gap g JOIN gap b ON g.tuned_on = b.tuned_on AND b.metric = 'ttr'"""
BEST_SQL = f"""WITH {GRID_CTES} SELECT tuned_on, metric, unit, n, lengths, signature, {_round_sql(*GRID_DOUBLES)} FROM (
  SELECT *, row_number() OVER (PARTITION BY tuned_on, metric, unit, lengths ORDER BY tune_value DESC, signature) AS place FROM grid WHERE tuned_on = tested_on) WHERE place = 1"""
_double = lambda c: f"(CASE WHEN {c} = floor({c}) THEN {c}::BIGINT || '.0' ELSE {c}::VARCHAR END)"
_PARAMETERS = {"n": "coalesce(n::VARCHAR, 'several')", "lengths": "lengths", "lam": _double("lam"), "eps": "'0.0'", "top_k": "'inf'", "g": "coalesce(g, 'none')", "d": "coalesce(d, 'none')", "asymptote": f"coalesce({_double('asymptote')}, 'inf')"}
EFFECT_SQL = f"""WITH {GRID_CTES}, x AS ({" UNION ALL ".join(f"SELECT tuned_on, metric, '{k}' AS parameter, {v} AS value, test_f1 FROM grid WHERE tuned_on = tested_on" for k, v in _PARAMETERS.items())})
SELECT tuned_on, metric, parameter, value, count(*) AS n_settings, round(max(test_f1) + 1e-10, 6) AS best_f1, round(avg(test_f1) + 1e-10, 6) AS mean_f1 FROM x GROUP BY ALL"""

# --- corpora --------------------------------------------------------------------------------------------


def score_vs_length(spark, sf_dir, cap=None):
    """Length, class, score and verdict at the learned boundary of every labelled document."""
    c = tasks.classified(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), cap, unsure=False)
    rows = tuning.with_verdict(c, MOMENT6, boundary(spark, sf_dir), places=6).where("score IS NOT NULL")
    return rows.select("doc_id", F.length("text").cast("bigint").alias("n_chars"), "label_class", "score", "is_natural")


SCATTER = f"""SELECT doc_id, length(text)::BIGINT AS n_chars, label_class, round(score + 1e-10, 6) AS score, round(score + 1e-10, 6) <= threshold AS is_natural
FROM ({moment_sql(MOMENT6, "_pchar6")}) JOIN classes USING (doc_id), line WHERE label_class <> 'unsure' AND score IS NOT NULL"""
SCATTER_SQL = f"WITH {MOMENT_CTES} {SCATTER}"


def length_boundary(spark, sf_dir):
    """The same points gathered by length."""
    return rounded(corpus.boundary_summary(score_vs_length(spark, sf_dir)), "mean_score")


BOUNDARY_SQL = f"""WITH {MOMENT_CTES} SELECT ((n_chars // 500) * 500)::BIGINT AS from_chars, label_class, count(*) AS n_docs, round(avg(score) + 1e-10, 6) AS mean_score, sum(is_natural::BIGINT)::BIGINT AS n_natural
FROM ({SCATTER}) GROUP BY ALL"""


def _cells(spark, sf_dir):
    """Everything the corpus reports need, one row a language and split: texts are read once and not moved for it."""
    rows = corpus.with_split(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"), table(spark, sf_dir, "labels"))
    return corpus.by_language(metrics.with_scores(rows, THREE), list(THREE))


def corpus_report(spark, sf_dir):
    """Mean scores of clean and noisy text, of languages with many and few documents."""
    return rounded(corpus.report_of(_cells(spark, sf_dir), list(THREE)), *[f"{k}_{s}" for k in ("micro", "macro") for s in THREE])


def corpus_report_lang(spark, sf_dir):
    """The same for each language."""
    return rounded(_cells(spark, sf_dir).select("lang", "tier", "split", "n_docs", *THREE), *THREE)


def tier_gap(spark, sf_dir):
    """Clean text of the languages with few documents beside noisy text of those with many."""
    return rounded(corpus.tier_gap(_cells(spark, sf_dir), list(THREE)), *THREE)


THREE_SQL = f"""{prof_sql()}, {prof_sql(n=4, tag="_4")},
y AS (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY doc_id),
base AS (SELECT doc_id, lang, CASE WHEN quality = 1 THEN 'clean' ELSE 'noisy' END AS split FROM documents JOIN y USING (doc_id)),
clean AS (SELECT lang, count(*) FILTER (split = 'clean') AS k FROM base GROUP BY lang),
tiers AS (SELECT lang, CASE WHEN k > (SELECT sum(k) / count(*) FROM clean) THEN 'high' ELSE 'low' END AS tier FROM clean),
three AS (SELECT b.doc_id, b.lang, b.split, t.tier, a.score AS ttr, m.score AS moment, z.score AS zipf FROM base b JOIN tiers t USING (lang)
  LEFT JOIN ({score_query_sql(TTR6)}) a USING (doc_id) LEFT JOIN ({score_query_sql(MOMENT6)}) m USING (doc_id) LEFT JOIN ({score_query_sql(ZIPF4, "_4")}) z USING (doc_id))"""
REPORT_SQL = f"""WITH {THREE_SQL}, l AS (SELECT split, tier, lang, count(*) AS n_docs, {", ".join(f"avg({s}) AS {s}, count({s}) AS n_{s}, sum({s}) AS sum_{s}" for s in THREE)} FROM three GROUP BY split, tier, lang)
SELECT split, tier, sum(n_docs)::BIGINT AS n_docs, count(DISTINCT lang) AS n_langs, {", ".join(f"round(sum(sum_{s}) / sum(n_{s}) + 1e-10, 6) AS micro_{s}, round(avg({s}) + 1e-10, 6) AS macro_{s}" for s in THREE)}
FROM l GROUP BY CUBE (split, tier)"""
MEANS_SQL = ", ".join(f"round(avg({s}) + 1e-10, 6) AS {s}" for s in THREE)
REPORT_LANG_SQL = f"WITH {THREE_SQL} SELECT lang, tier, split, count(*) AS n_docs, {MEANS_SQL} FROM three GROUP BY lang, tier, split"
GAP_SQL = f"WITH {THREE_SQL} SELECT split, tier, count(*) AS n_docs, {MEANS_SQL} FROM three WHERE (split = 'clean' AND tier = 'low') OR (split = 'noisy' AND tier = 'high') GROUP BY split, tier"


def base_rate_table(spark, sf_dir):
    """Purity of what a filter passes, by base rate and rate of false alarms."""
    priors = spark.createDataFrame([(x,) for x in (1e-5, 1e-4, 1e-3, 0.01, 0.1)], "prior double")
    rates = spark.createDataFrame([(x,) for x in (0.1, 0.01, 0.001)], "fpr double")
    purity = measures.base_rate_purity(F.col("prior"), F.lit(1.0), F.col("fpr"))
    return priors.crossJoin(F.broadcast(rates)).withColumn("purity", F.round(purity, 9))


BASE_RATE_SQL = """SELECT prior, fpr, round(prior / (prior + (1 - prior) * fpr), 9) AS purity
FROM (SELECT unnest([1e-5, 1e-4, 1e-3, 0.01, 0.1]::DOUBLE[]) AS prior), (SELECT unnest([0.1, 0.01, 0.001]::DOUBLE[]) AS fpr)"""


def signatures(spark, sf_dir):
    """The released settings by signature, each read back."""
    return tuning.settings_table(spark, [parse_signature(signature(s)) for s in RELEASED])


SIGNATURES_SQL = r"""WITH raw(setting, signature) AS (VALUES """ + ", ".join(f"({i}, '{signature(s)}')" for i, s in enumerate(RELEASED)) + r"""),
first AS (SELECT *, signature LIKE 'mean(%' AS mixed, regexp_extract(signature, '(ttr|moment|zipf)\|[^;)]*') AS one FROM raw),
f AS (SELECT *, regexp_extract(one, '^[a-z]+') AS metric, regexp_extract(one, 'u=([a-z]+)', 1) AS unit, regexp_extract(one, '\|n=(\d+)', 1)::INTEGER AS n, regexp_extract(one, '\|g=([a-z_]+)', 1) AS g, regexp_extract(one, '\|g=pow([0-9.]+)', 1) AS k, regexp_extract(one, '\|d=([a-z_]+)', 1) AS d, regexp_extract(one, '\|A=([0-9.]+)', 1) AS a,
  regexp_extract_all(signature, 'u=[a-z]+\|n=\d+') AS parts FROM first)
SELECT setting::INTEGER AS setting, signature, metric, unit, CASE WHEN NOT mixed THEN n END AS n, CASE WHEN mixed THEN array_to_string(list_transform(parts, lambda p: replace(replace(p, 'u=', ''), '|n=', ':')), '+') ELSE unit || ':' || n END AS lengths,
  regexp_extract(one, 'lam=([0-9.]+)', 1)::DOUBLE AS lam, regexp_extract(one, 'eps=([0-9.]+)', 1)::DOUBLE AS eps, NULL::INTEGER AS top_k,
  CASE WHEN metric = 'moment' THEN g END AS g, CASE WHEN metric = 'moment' AND k <> '' THEN k::DOUBLE END AS k, CASE WHEN metric = 'zipf' THEN d END AS d, CASE WHEN a <> '' THEN a::DOUBLE END AS asymptote FROM f"""


def filter_corpus(spark, sf_dir):
    """Documents and characters that stay at the learned boundary, by language and source."""
    docs = table(spark, sf_dir, "documents").select("text", "lang", "source")
    kept = tuning.filter_natural(src.spread(docs), MOMENT6, boundary(spark, sf_dir), places=6)
    return kept.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(F.length("text").cast("bigint")).alias("n_chars"))


ALL_MOMENTS = f"SELECT d.doc_id, lang, source, text, round(score + 1e-10, 6) AS score, threshold FROM documents d LEFT JOIN ({moment_sql(MOMENT6)}) USING (doc_id), line"
FILTER_SQL = f"""WITH {MOMENT_CTES}, {prof_sql()} SELECT lang, source, count(*) AS n_docs, sum(length(text))::BIGINT AS n_chars
FROM ({ALL_MOMENTS}) WHERE coalesce(score <= threshold, true) GROUP BY lang, source"""


def partition_verdicts(spark, sf_dir):
    """Every document with its verdict at the learned boundary, rejects too."""
    verdict = F.when(F.col("is_natural"), "natural").when(~F.col("is_natural"), "rejected").otherwise("too short").alias("verdict")
    return tuning.partition_by_verdict(texts(spark, sf_dir), MOMENT6, boundary(spark, sf_dir), places=6).select("doc_id", "score", verdict)


VERDICT_SQL = f"WITH {MOMENT_CTES}, {prof_sql()} SELECT doc_id, score, CASE WHEN score <= threshold THEN 'natural' WHEN score > threshold THEN 'rejected' ELSE 'too short' END AS verdict FROM ({ALL_MOMENTS})"

PAIR = {"first": MOMENT6, "second": MOMENT6.but(asymptote=500.0)}


def verdict_changes(spark, sf_dir):
    """Documents on which two settings disagree, each at its own learned boundary; texts are counted once for both."""
    lines = _learned(spark, sf_dir, PAIR).where("operating_point = 'balanced_f1'").groupBy().agg(*[F.max(F.when(F.col("name") == k, F.col("threshold"))).alias(f"{k}_at") for k in PAIR])
    rows = metrics.with_scores(texts(spark, sf_dir), PAIR).crossJoin(F.broadcast(lines))
    rows = rows.select("doc_id", *[(tuning.rounded_score(k) <= F.col(f"{k}_at")).alias(k) for k in PAIR])
    return rows.where(~F.col("first").eqNullSafe(F.col("second")))


CHANGES_SQL = f"""WITH {_points_ctes(PAIR)}, {prof_sql()},
lines AS (SELECT max(threshold) FILTER (name = 'first') AS a, max(threshold) FILTER (name = 'second') AS b FROM points WHERE operating_point = 'balanced_f1'),
v AS (SELECT d.doc_id, round(x.score + 1e-10, 6) <= a AS first, round(y.score + 1e-10, 6) <= b AS second FROM documents d LEFT JOIN ({moment_sql(PAIR["first"])}) x USING (doc_id) LEFT JOIN ({moment_sql(PAIR["second"])}) y USING (doc_id), lines)
SELECT * FROM v WHERE first IS DISTINCT FROM second"""


def threshold_versions(spark, sf_dir):
    """Each document with the boundary that held when it came in: documents arrive in order of id, and two versions of the boundary take effect one after the other."""
    s = metrics.score_documents(texts(spark, sf_dir), MOMENT6).where("valid").select("doc_id", "signature", F.round(F.col("score") + NUDGE, 6).alias("score"), F.col("doc_id").alias("at"))
    versions = spark.createDataFrame([(signature(MOMENT6), 1.5, 50), (signature(MOMENT6), 1.2, 120)], "signature string, threshold double, at bigint")
    return tuning.threshold_as_of(s, versions).select("doc_id", "score", "threshold", (F.col("score") <= F.col("threshold")).alias("is_natural"))


VERSIONS_SQL = f"""WITH {prof_sql()}, v(threshold, since) AS (VALUES (1.5::DOUBLE, 50), (1.2::DOUBLE, 120)), s AS (SELECT doc_id, round(score + 1e-10, 6) AS score FROM ({moment_sql(MOMENT6)}) WHERE score IS NOT NULL)
SELECT doc_id, score, threshold, score <= threshold AS is_natural FROM s ASOF LEFT JOIN v ON s.doc_id >= v.since"""


def worst_documents(spark, sf_dir):
    """The twenty most repetitive documents."""
    return one_score(MOMENT6, spark, sf_dir).where("score IS NOT NULL").select("doc_id", "score").orderBy(F.desc("score"), "doc_id").limit(20)


def vocabulary_size(spark, sf_dir):
    """3-grams of each language and roughly how many differ: one pass with a sketch for each task."""
    docs = table(spark, sf_dir, "documents")
    return corpus.approximate_profile(docs.select("lang", F.explode(sp.char_ngrams(F.col("text"), 3)).alias("gram")), "lang")


def score_quantiles(spark, sf_dir):
    """Approximate quantiles of the three scores."""
    return corpus.score_quantiles(metrics.score_documents(texts(spark, sf_dir), list(THREE.values())))


def run_cost(spark, sf_dir):
    """What scoring every document costs: documents, characters, bytes of spectra to a document, and the shuffles in its plan."""
    docs = texts(spark, sf_dir)
    return measures.run_cost(metrics.score_documents(docs, MOMENT6), docs, sp.spectra(docs, [MOMENT6.spec]))


# --- documents from other tables -----------------------------------------------------------------------


def derived(make, spark, sf_dir):
    """Scores of documents made from another table's rows, over their whole texts."""
    return rounded(metrics.score_documents(make(spark, sf_dir), MOMENT6).select("doc_id", "n_total", "score"), "score")


def catalogue_docs_score(spark, sf_dir):
    """Scores of each brand's whole price list, counted line by line: no list is ever one row."""
    x = sp.line_spectra(table(spark, sf_dir, "part"), "p_brand", ["p_partkey"], src.catalogue_line(), 6)
    return rounded(metrics.score(x, MOMENT6).select("doc_id", "n_total", "score"), "score")


def _pages(spark, sf_dir):
    return src.page_docs(table(spark, sf_dir, "pages")).select(F.concat_ws(":", "doc_id", "variant").alias("doc_id"), "text")


def _conversations(spark, sf_dir):
    turns = table(spark, sf_dir, "conversations")
    named = lambda d, r: d.select(F.concat_ws(":", "doc_id", F.lit(r)).alias("doc_id"), "text")
    return named(src.conversation_docs(turns), "all").unionByName(named(src.conversation_docs(turns, "user"), "user")).unionByName(named(src.conversation_docs(turns, "assistant"), "assistant"))


CATALOGUE_SQL = "SELECT p_brand AS doc_id, string_agg(concat_ws(' ', p_name, p_type, 'size', p_size, '$' || printf('%.2f', p_retailprice)), chr(10) ORDER BY p_partkey) AS text FROM part GROUP BY p_brand"
LOGS_SQL = "SELECT user_id AS doc_id, string_agg(concat_ws(' ', strftime(ts, '%Y-%m-%d %H:%M:%S'), event_type, printf('%.2f', value)), chr(10) ORDER BY ts, event_id) AS text FROM events GROUP BY user_id"
DERIVED = {
    "event_log_score": (lambda spark, d: src.event_log_docs(table(spark, d, "events")), LOGS_SQL),
    "conversation_score": (
        _conversations,
        "SELECT conv_id || ':' || r AS doc_id, string_agg(coalesce(text, ''), chr(10) ORDER BY turn) AS text FROM conversations, (SELECT unnest(['all', 'user', 'assistant']) AS r) WHERE r = 'all' OR role = r GROUP BY conv_id, r",
    ),
    "benchmark_reference": (
        lambda spark, d: table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), "text"),
        "SELECT item_id AS doc_id, text FROM benchmark",
    ),
    "page_boilerplate": (_pages, None),
}
_BARE = "trim(regexp_replace(regexp_replace(regexp_replace({}, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]*>', ' ', 'g'), '[ \\t\\r\\n]+', ' ', 'g'))"
PAGES_SQL = f"""SELECT page_id || ':html' AS doc_id, html AS text FROM pages UNION ALL SELECT page_id || ':stripped', {_BARE.format("html")} FROM pages
UNION ALL SELECT page_id || ':article', {_BARE.format("regexp_extract(html, '<article[^>]*>(.*?)</article>', 1, 's')")} FROM pages"""


def derived_sql(docs: str) -> str:
    return f"WITH made AS ({docs}), {prof_sql(docs='SELECT doc_id, text FROM made')}\n{all_docs_sql(moment_sql(MOMENT6), 'made')}"


def sink_by_verdict(spark, sf_dir):
    """Documents written to a folder for each verdict and read back: how many there are of each, and their mean score."""
    path = fresh_path(spark, "verdicts")
    sinks.write_scored(partition_verdicts(spark, sf_dir), path, partition_by=("verdict",))
    back = spark.read.parquet(path)
    return rounded(back.groupBy("verdict").agg(F.count(F.lit(1)).alias("n_docs"), F.avg("score").alias("mean_score")), "mean_score")


SINK_SQL = f"SELECT verdict, count(*) AS n_docs, round(avg(score) + 1e-10, 6) AS mean_score FROM ({VERDICT_SQL}) GROUP BY verdict"
ROUND_TRIPS = ("parquet", "orc", "json", "csv")


def source_formats(spark, sf_dir):
    """Benchmark passages through each file format and the reader: their scores come out the same."""
    rows = table(spark, sf_dir, "benchmark").select("item_id", "text")
    parts = []
    for name in ROUND_TRIPS:
        path = fresh_path(spark, name)
        rows.write.format(name).options(**({"header": True, "escape": '"'} if name == "csv" else {})).save(path)
        docs = src.read_documents(spark, path, name, "item_id", "text", "item_id bigint, text string" if name in ("json", "csv") else None)
        parts.append(metrics.score_documents(docs, MOMENT6).select(F.lit(name).alias("format"), "doc_id", "score"))
    return rounded(functools.reduce(DataFrame.unionByName, parts), "score")


FORMATS_SQL = f"""WITH made AS (SELECT item_id AS doc_id, text FROM benchmark), {prof_sql(docs="SELECT doc_id, text FROM made")}
SELECT f AS format, doc_id, score FROM ({all_docs_sql(moment_sql(MOMENT6), "made")}), (SELECT unnest([{", ".join(repr(f) for f in ROUND_TRIPS)}]) AS f)"""


# --- streams --------------------------------------------------------------------------------------------


def stream_scored(spark, sf_dir):
    """Documents scored through a stream: what a batch gives."""
    path = f"{sf_dir}/documents.parquet"
    docs = streaming.read_stream(spark, path) if os.path.isdir(path) else streaming.read_stream(spark, sf_dir, glob="documents.parquet")
    out = streaming.run_to_files(streaming.scored_stream(docs, MOMENT6), fresh_path(spark, "stream"))
    return rounded(out.select("doc_id", "n_total", "score"), "score")


def _event_stream(spark, sf_dir):
    return spark.readStream.schema(table(spark, sf_dir, "events").schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def stream_event_windows(spark, sf_dir):
    """Redundancy of each user's event types per hour, through a stream whose updates go to files."""
    out = streaming.run_updates(streaming.event_windows(_event_stream(spark, sf_dir)), fresh_path(spark, "windows"), ["window_start", "user_id"])
    return out.select(F.date_format("window_start", "yyyy-MM-dd HH:mm:ss").alias("window_start"), "user_id", "n_events", "n_types", F.round(F.col("moment") + NUDGE, 6).alias("moment"))


STREAM_WINDOWS_SQL = """WITH k AS (SELECT date_trunc('hour', ts) AS w, user_id, event_type, count(*) AS c FROM events GROUP BY ALL)
SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS window_start, user_id, sum(c)::BIGINT AS n_events, count(*) AS n_types, round(sum(c::DOUBLE * c) / power(sum(c), 2) + 1e-10, 6) AS moment FROM k GROUP BY w, user_id"""


def stream_user_moments(spark, sf_dir):
    """Redundancy of each user's event types since the beginning, from counts that the stream keeps by user."""
    out = streaming.run_updates(streaming.user_moments(_event_stream(spark, sf_dir)), fresh_path(spark, "users"), ["user_id"])
    return rounded(out.select("user_id", "n_events", "n_types", "moment"), "moment")


USER_MOMENTS_SQL = """SELECT user_id, sum(c)::BIGINT AS n_events, count(*) AS n_types, round(sum(c::DOUBLE * c) / power(sum(c), 2) + 1e-10, 6) AS moment
FROM (SELECT user_id, event_type, count(*) AS c FROM events GROUP BY ALL) GROUP BY user_id"""


def stream_sessions(spark, sf_dir):
    """Sessions of each user (events less than half an hour apart) and how redundant their types are, through a stream."""
    out = streaming.run_updates(streaming.event_sessions(_event_stream(spark, sf_dir)), fresh_path(spark, "sessions"), ["session_start", "user_id"])
    return out.select(F.date_format("session_start", "yyyy-MM-dd HH:mm:ss").alias("session_start"), "user_id", "n_events", "n_types", F.round(F.col("moment") + NUDGE, 6).alias("moment"))


SESSIONS_SQL = """WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g),
k AS (SELECT user_id, no, min(ts) AS t, event_type, count(*) AS c FROM s GROUP BY user_id, no, event_type)
SELECT strftime(min(t), '%Y-%m-%d %H:%M:%S') AS session_start, user_id, sum(c)::BIGINT AS n_events, count(*) AS n_types, round(sum(c::DOUBLE * c) / power(sum(c), 2) + 1e-10, 6) AS moment FROM k GROUP BY user_id, no"""


def stream_distinct_texts(spark, sf_dir):
    """Events of which each content (user, type, value) is taken once, through a stream that remembers what it has seen."""
    events = _event_stream(spark, sf_dir).select("user_id", "event_type", "value", F.col("ts").cast("timestamp").alias("at"))
    once = streaming.first_of_each(events, ["user_id", "event_type", "value"], "at", "3650 days")
    out = streaming.run_to_files(once.select("user_id", "event_type", "value"), fresh_path(spark, "distinct"))
    return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n_distinct"))


DISTINCT_SQL = "SELECT event_type, count(*) AS n_distinct FROM (SELECT DISTINCT user_id, event_type, value FROM events) GROUP BY event_type"


def sql_surface(spark, sf_dir):
    """Scores through the SQL function, as a user of SQL would ask for them."""
    sql_functions.register(spark)
    return rounded(texts(spark, sf_dir).selectExpr("doc_id", f"redundancy(text, '{signature(MOMENT6)}') AS score"), "score")


def sql_ngrams(spark, sf_dir):
    """How often each word pair occurs in benchmark passages, by the table function."""
    sql_functions.register(spark)
    return spark.sql("SELECT gram, count(*) AS cnt FROM {b}, LATERAL ngrams(text, 'token', 2) GROUP BY gram", b=table(spark, sf_dir, "benchmark"))


SQL_NGRAMS_SQL = """WITH w AS (SELECT list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '') AS t FROM benchmark)
SELECT t[i] || ' ' || t[i + 1] AS gram, count(*) AS cnt FROM w, unnest(range(1, len(t)::BIGINT)) AS u(i) GROUP BY gram"""


def sql_spectrum(spark, sf_dir):
    """Spectra of 3-grams of benchmark passages, by the table function."""
    sql_functions.register(spark)
    return spark.sql("SELECT item_id, c, v FROM {b}, LATERAL spectrum(text, 'char', 3)", b=table(spark, sf_dir, "benchmark"))


SQL_SPECTRUM_SQL = f"""WITH {prof_sql(n=3, docs="SELECT item_id AS doc_id, text FROM benchmark")} SELECT doc_id AS item_id, c::BIGINT AS c, count(*) AS v FROM prof GROUP BY doc_id, c"""


SINGLE = {
    "ttr_char6": TTR6,
    "ttr_token1": Setting(metric="ttr", unit="token", n=1),
    "moment_sq_char6": MOMENT6,
    "moment_p15": MOMENT6.but(k=1.5),
    "moment_cube": MOMENT6.but(k=3.0),
    "moment_entropy": MOMENT6.but(g="entropy"),
    "moment_sq_entropy": MOMENT6.but(g="sq_entropy"),
    "moment_smoothed": MOMENT6.but(lam=0.1),
    "moment_eps": MOMENT6.but(eps=1.0),
    "moment_topk": MOMENT6.but(top_k=100),
    "moment_token2": Setting(unit="token", n=2),
    "zipf_sq_char4": ZIPF4,
    "zipf_shifted": ZIPF4.but(exponent=1.1, shift=2.7),
    "zipf_log": ZIPF4.but(d="log", norm="difference"),
    "zipf_sq_log": ZIPF4.but(d="sq_log", norm="difference"),
    "zipf_jsd": ZIPF4.but(d="jsd"),
    "zipf_kl": ZIPF4.but(d="kl_pq"),
    "zipf_kl_reverse": ZIPF4.but(d="kl_qp"),
    "zipf_abs": ZIPF4.but(d="abs"),
    "zipf_bounded": ZIPF4.but(support="bounded"),
    "moment_line1": Setting(unit="line", n=1),
    "moment_hyperbolic": MOMENT6.but(mode="hyperbolic"),
    "moment_exponential": MOMENT6.but(mode="exponential"),
    "moment_difference": MOMENT6.but(norm="difference"),
    "moment_raw": MOMENT6.but(norm="none"),
    "moment_eps_prob": MOMENT6.but(eps=0.001, eps_on="prob"),
    "ttr_clipped": TTR6.but(eps=1.0),
    "ttr_topk_smoothed": TTR6.but(top_k=100, lam=0.1),
}
SEVERAL = {
    "ttr_multi": [TTR6, TTR6.but(n=4), TTR6.but(n=8)],
    "lengthnorm_sweep": [MOMENT6.but(asymptote=a) for a in (500.0, 1000.0, 2000.0, 5000.0, math.inf)],
}
NAMED = {
    "toy_histogram": (toy_histogram, TOY_SQL),
    "class_counts": (class_counts, f"WITH {CLASSES_SQL} SELECT label_class, count(*) AS n_docs FROM classes GROUP BY label_class"),
    "split_balance": (split_balance, f"WITH {CLASSES_SQL} SELECT label_class, half, count(*) AS n_docs FROM classes GROUP BY label_class, half"),
    "language_cover": (language_cover, f"WITH {CLASSES_SQL} SELECT lang, count(*) AS n_natural, least(count(*), 6)::BIGINT AS n_sampled FROM classes WHERE label_class = 'natural' GROUP BY lang"),
    "profile_char6": (profile_char6, PROFILE_SQL),
    "spectra_native": (partial(strategy_twin, "native"), TWIN_SQL),
    "spectra_relational": (partial(strategy_twin, "relational"), TWIN_SQL),
    "window_ttr": (window_ttr, WINDOW_SQL),
    "window_ttr_steps": (window_ttr_steps, WINDOW_STEPS_SQL),
    "own_nonlinearity": (own_nonlinearity, f"WITH {prof_sql()} SELECT d.doc_id, round(x + 1e-10, 6) AS score FROM documents d LEFT JOIN (SELECT doc_id, sum(power(c / t, 1.2)) AS x FROM (SELECT *, sum(c) OVER (PARTITION BY doc_id) AS t FROM prof) GROUP BY doc_id) USING (doc_id)"),
    "corpus_histogram": (corpus_histogram, CORPUS_HISTOGRAM_SQL),
    "pooled_moment": (pooled_moment, POOLED_MOMENT_SQL),
    "ttr_capped": (ttr_capped, f"WITH {prof_sql(cap=505)}\n{all_docs_sql(score_query_sql(TTR6))}"),
    "verdict_changes": (verdict_changes, CHANGES_SQL),
    "worst_documents": (worst_documents, f"SELECT doc_id, score FROM ({one_score_sql(MOMENT6)}) WHERE score IS NOT NULL ORDER BY score DESC, doc_id LIMIT 20"),
    "zipf_empirical": (zipf_empirical, ZIPF_EMPIRICAL_SQL),
    "rank_model_fit": (rank_model_fit, FIT_SQL),
    "ensemble_char_token": (ensemble_char_token, ENSEMBLE_SQL),
    "ensemble_standardised": (ensemble_standardised, STANDARDISED_SQL),
    "grid_repeat": (partial(small_grid, "repeat"), small_grid_sql("repeat")),
    "grid_noise": (partial(small_grid, "noise"), small_grid_sql("noise")),
    "grid_noise_capped": (partial(small_grid, "noise", cap=sp.BENCHMARK_CAP), small_grid_sql("noise", sp.BENCHMARK_CAP)),
    "grid_repeat_plus": (grid_repeat_plus, small_grid_sql("repeat", extra=f"SELECT text FROM ({CATALOGUE_SQL}) UNION ALL SELECT text FROM ({LOGS_SQL})")),
    "grid_full": (grid_full, GRID_SQL),
    "threshold_curve": (threshold_curve, CURVE_SQL),
    "constant_baseline": (constant_baseline, CONSTANT_SQL),
    "operating_points": (operating_points, POINTS_SQL),
    "tune_test_matrix": (tune_test_matrix, MATRIX_SQL),
    "relative_gain": (relative_gain, GAIN_SQL),
    "best_setting_per_n": (best_setting_per_n, BEST_SQL),
    "parameter_effect": (parameter_effect, EFFECT_SQL),
    "grid_overfit": (grid_overfit, None),
    "score_vs_length": (score_vs_length, SCATTER_SQL),
    "length_boundary": (length_boundary, BOUNDARY_SQL),
    "corpus_report": (corpus_report, REPORT_SQL),
    "corpus_report_lang": (corpus_report_lang, REPORT_LANG_SQL),
    "tier_gap": (tier_gap, GAP_SQL),
    "base_rate_table": (base_rate_table, BASE_RATE_SQL),
    "signatures": (signatures, SIGNATURES_SQL),
    "filter_corpus": (filter_corpus, FILTER_SQL),
    "partition_verdicts": (partition_verdicts, VERDICT_SQL),
    "threshold_versions": (threshold_versions, VERSIONS_SQL),
    "sink_by_verdict": (sink_by_verdict, SINK_SQL),
    "source_formats": (source_formats, FORMATS_SQL),
    "vocabulary_size": (vocabulary_size, None),
    "score_quantiles": (score_quantiles, None),
    "run_cost": (run_cost, None),
    "catalogue_docs_score": (catalogue_docs_score, f"WITH made AS ({CATALOGUE_SQL}), {prof_sql(docs='SELECT doc_id, text FROM made')}\n{all_docs_sql(moment_sql(MOMENT6), 'made')}"),
    "stream_scored": (stream_scored, one_score_sql(MOMENT6)),
    "stream_event_windows": (stream_event_windows, STREAM_WINDOWS_SQL),
    "stream_user_moments": (stream_user_moments, USER_MOMENTS_SQL),
    "stream_sessions": (stream_sessions, SESSIONS_SQL),
    "stream_distinct_texts": (stream_distinct_texts, DISTINCT_SQL),
    "sql_ngrams": (sql_ngrams, SQL_NGRAMS_SQL),
    "sql_spectrum": (sql_spectrum, SQL_SPECTRUM_SQL),
    "sql_surface": (sql_surface, f"SELECT doc_id, score FROM ({one_score_sql(MOMENT6)})"),
}


def queries() -> dict:
    out = {k: partial(one_score, s) for k, s in SINGLE.items()} | {k: partial(many_scores, s) for k, s in SEVERAL.items()}
    return out | {k: q for k, (q, _) in NAMED.items()} | {k: partial(derived, make) for k, (make, _) in DERIVED.items()}


def oracle_sql() -> dict[str, str]:
    out = {k: one_score_sql(s) for k, s in SINGLE.items()} | {k: many_scores_sql(s) for k, s in SEVERAL.items()}
    out |= {k: q for k, (_, q) in NAMED.items() if q}
    return out | {k: derived_sql(q or PAGES_SQL) for k, (_, q) in DERIVED.items()}
