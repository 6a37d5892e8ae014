"""Scores of documents and of spectra.

``with_scores`` adds scores to the rows of a table: one function of the text counts and scores in
numpy, only texts go to the workers and only scores come back, and nothing is shuffled or joined.
``score`` does so for spectra that are kept for reuse; ``native_score`` is the same for the
settings that array functions can say (all but the rank-by-rank distances), and stays in the JVM.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from textredun.functions.signature import Ensemble, Setting, members, signature
from textredun.operators import kernel
from textredun.operators.spectrum import id_field, require_columns
from textredun.operators.spectrum import spectra as spectra_of_docs

TINY = 1e-12


def effective_length(n, asymptote: float = 2000.0, mode: str = "clamp"):
    """The length that a document of ``n`` n-grams is compared at: it levels off at ``asymptote``."""
    n = np.asarray(n, dtype=float)
    if math.isinf(asymptote):
        return n
    if mode == "clamp":
        return np.minimum(n, asymptote)
    if mode == "hyperbolic":
        return n * asymptote / (n + asymptote)
    return asymptote * (1 - np.exp(-n / asymptote))


def nonlinear(p: np.ndarray, s: Setting) -> np.ndarray:
    if s.g == "pow":
        return p**s.k
    log = np.log(np.where(p > 0, p, 1.0))
    return -p * log if s.g == "entropy" else (p * log) ** 2


def distance(q: np.ndarray, p: np.ndarray, d: str) -> np.ndarray:
    """Distance of an expected share q from a share p; logarithms have a floor of ``TINY``."""
    if d == "sq":
        return (q - p) ** 2
    if d == "abs":
        return np.abs(q - p)
    if d in ("log", "sq_log"):
        log = np.log(np.maximum(np.abs(q - p), TINY))
        return log if d == "log" else log * log
    safe_p, safe_q = np.where(p > 0, p, 1.0), np.where(q > 0, q, 1.0)
    if d == "jsd":
        m = (p + q) / 2
        safe_m = np.where(m > 0, m, 1.0)
        return 0.5 * (p * np.log(safe_p / safe_m) + q * np.log(safe_q / safe_m))
    floor_p, floor_q = np.maximum(p, TINY), np.maximum(q, TINY)
    return p * np.log(safe_p / floor_q) if d == "kl_pq" else q * np.log(safe_q / floor_p)


class RankModel:
    """Unnormalised expected shares of ranks 1, 2, ... and their running sums, as long as asked for.

    ``shares`` gives them one by one; with ``ends``, each holds for all ranks behind the end before, up to its own.
    """

    def __init__(self, exponent: float = 1.0, shift: float = 0.0, shares: Sequence[float] | None = None, ends: Sequence[int] | None = None):
        self.exponent, self.shift, self.shares, self.ends = exponent, shift, shares, ends
        self.q = self.sum_q = self.sum_q2 = np.zeros(0)

    def upto(self, ranks: int) -> RankModel:
        if len(self.q) < ranks:
            size = max(ranks, 2 * len(self.q), 5000)
            if self.shares is None:
                self.q = (np.arange(1, size + 1) + self.shift) ** -self.exponent
            else:
                self.q = np.zeros(size)
                ends = np.arange(1, len(self.shares) + 1) if self.ends is None else np.asarray(self.ends)
                known = np.repeat(np.asarray(self.shares, dtype=float), np.diff(np.minimum(ends, size), prepend=0))
                self.q[: len(known)] = known
            self.sum_q = np.concatenate([[0.0], np.cumsum(self.q)])
            self.sum_q2 = np.concatenate([[0.0], np.cumsum(self.q**2)])
        return self


def power_model(exponent: float, shift: float) -> RankModel:
    """Each worker makes a model once."""
    return kernel.kept(("power model", exponent, shift), lambda: RankModel(exponent, shift))


def uniform_reference(s: Setting, m: np.ndarray, model: RankModel | None = None) -> np.ndarray:
    """The score of a document of (effective) length m without any repetition."""
    m = np.asarray(m, dtype=float)
    safe = np.maximum(m, TINY)
    if s.metric == "ttr":
        return np.ones_like(m)
    if s.metric == "moment":
        if s.g == "pow":
            return safe ** (1 - s.k)
        return np.log(safe) if s.g == "entropy" else np.log(safe) ** 2 / safe
    ranks = np.maximum(m, 0).astype(np.int64)
    known = {} if model else kernel.kept(("uniform reference", s.d, s.exponent, s.shift), dict)
    model = (model or power_model(s.exponent, s.shift)).upto(int(ranks.max(initial=1)))
    scale = np.maximum(model.sum_q[ranks], TINY)
    if s.d == "sq":
        return np.where(ranks > 0, model.sum_q2[ranks] / scale**2 - 2 * model.sum_q[ranks] / scale / safe + ranks / safe**2, 0.0)
    values, which = np.unique(m, return_inverse=True)
    out = np.zeros(len(values))
    for i, value in enumerate(values.tolist()):
        if value >= 1:
            if value not in known:
                r = int(value)
                known[value] = float(distance(model.q[:r] / max(model.sum_q[r], TINY), np.full(r, 1 / value), s.d).sum())
            out[i] = known[value]
    return out[which].reshape(m.shape)


def shares(c: np.ndarray, v: np.ndarray, doc: np.ndarray, n_total: np.ndarray, s: Setting) -> tuple[np.ndarray, np.ndarray]:
    """(kept v, share p of each n-gram) of the entries of spectra after clipping and smoothing; dropped entries have v = 0."""
    v = v.copy()
    keep = c > s.eps if s.eps_on == "count" else c > s.eps * n_total[doc]
    v[~keep] = 0
    if s.top_k is not None and len(v):
        run = np.cumsum(v)
        first = np.searchsorted(doc, np.arange(len(n_total)))
        before = run - v - (run - v)[np.minimum(first, len(v) - 1)][doc]
        v = np.clip(s.top_k - before, 0, v)
    w = c + s.lam
    z = np.bincount(doc, weights=v * w, minlength=len(n_total))
    return v, w / np.maximum(z, TINY)[doc]


def score_spectra(c, v, ends, n_total, n_types, s: Setting, model: RankModel | None = None, known: dict | None = None) -> np.ndarray:
    """Scores of documents whose spectra are ``ends[i]:ends[i+1]`` of (c, v); NaN where there is no n-gram, or nothing to divide by.

    ``known`` keeps what settings that differ in their length compensation alone have in common.
    """
    docs = len(n_total)
    n_total = np.asarray(n_total, dtype=float)
    m = effective_length(n_total, s.asymptote, s.mode)
    key = s if s.support == "bounded" else (s.metric, s.lam, s.eps, s.eps_on, s.top_k, s.g, s.k, s.d, s.exponent, s.shift)
    raw = None if known is None else known.get(key)
    if raw is None:
        raw = _raw(np.asarray(c, dtype=float), np.asarray(v, dtype=float), np.repeat(np.arange(docs), np.diff(ends)), n_total, n_types, m, s, model)
        if known is not None:
            known[key] = raw
    if s.metric == "ttr":
        return np.where(n_total > 0, raw, np.nan)
    if s.g == "entropy" and s.metric == "moment" and s.norm != "none":
        # entropy is highest without repetition: turned round, 0 is none and 1 is all
        log_m = np.log(np.maximum(m, 1.0))
        return np.where((n_total > 0) & (log_m > 0), 1 - raw / np.maximum(log_m, TINY), np.nan)
    if s.norm == "none":
        return np.where(n_total > 0, raw, np.nan)
    reference = uniform_reference(s, m, model)
    if s.norm == "difference":
        return np.where(n_total > 0, raw - reference, np.nan)
    ok = (n_total > 0) & (np.abs(reference) > TINY)
    return np.where(ok, raw / np.where(ok, reference, 1.0), np.nan)


def _raw(c, v, doc, n_total, n_types, m, s: Setting, model: RankModel | None) -> np.ndarray:
    """Scores before length compensation, for documents with n-grams."""
    docs = len(n_total)
    if s.metric == "ttr":
        types, mass = n_types, n_total
        if s.lam or s.eps or s.top_k is not None:
            v, _ = shares(c, v, doc, n_total, s)
            types, mass = np.bincount(doc, weights=v, minlength=docs), np.bincount(doc, weights=v * (c + s.lam), minlength=docs)
        return np.where(mass > 0, 1 - types / np.where(mass > 0, mass, 1.0), 0.0)
    v, p = shares(c, v, doc, n_total, s)
    if s.metric == "moment":
        return np.bincount(doc, weights=v * nonlinear(p, s), minlength=docs)
    return _zipf(v, p, doc, docs, m, s, model)


def _zipf(v, p, doc, docs, m, s: Setting, model: RankModel | None) -> np.ndarray:
    model = model or power_model(s.exponent, s.shift)
    types = np.bincount(doc, weights=v, minlength=docs).astype(np.int64)
    support = types if s.support == "observed" else np.maximum(types, m.astype(np.int64))
    model.upto(int(support.max(initial=1)))
    scale = np.maximum(model.sum_q[support], TINY)
    v = v.astype(np.int64)
    after = np.cumsum(v)
    start = np.concatenate([[0], np.cumsum(types)])[:-1]
    after = after - start[doc]
    before = after - v
    if s.d == "sq":
        cross, squares = model.sum_q[after] - model.sum_q[before], model.sum_q2[after] - model.sum_q2[before]
        out = np.bincount(doc, weights=v * p * p - 2 * p * cross / scale[doc] + squares / scale[doc] ** 2, minlength=docs)
        return out + (model.sum_q2[support] - model.sum_q2[types]) / scale**2
    rank_doc, rank_p = np.repeat(doc, v), np.repeat(p, v)
    rank = np.arange(len(rank_doc)) - start[rank_doc]
    out = np.bincount(rank_doc, weights=distance(model.q[rank] / scale[rank_doc], rank_p, s.d), minlength=docs)
    for i in np.flatnonzero(support > types):
        q = model.q[types[i] : support[i]] / scale[i]
        out[i] += distance(q, np.zeros(len(q)), s.d).sum()
    return out


def score_texts(texts: list[str | None], settings: Sequence[Setting | Ensemble], models: Mapping[int, RankModel] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(number of n-grams [text, spec], scores [text, setting]); NaN where a score is not valid.

    Specs are the different (unit, n) of the settings in order; texts are cut as a setting's ``cap`` says.
    An ensemble is the mean of its members' valid scores.
    """
    texts = [t or "" for t in texts]
    flat = list(dict.fromkeys(m for s in settings for m in members(s)))
    at = {s: i for i, s in enumerate(flat)}
    specs = {spec: i for i, spec in enumerate(specs_of(settings))}
    totals, out = np.zeros((len(texts), len(specs)), dtype=np.int64), np.full((len(texts), len(flat)), np.nan)
    wanted: dict[tuple, dict[int, list[Setting]]] = {}
    for s in flat:
        wanted.setdefault((s.cap, s.unit), {}).setdefault(s.n, []).append(s)
    for (cap, unit), by_n in wanted.items():
        for begin, part in kernel.slices(texts if cap is None else [t[:cap] for t in texts]):
            rows = slice(begin, begin + len(part))
            for n, total, types, ends, c, v in kernel.spectra_of(*kernel.units_of(part, unit), list(by_n)):
                totals[rows, specs[unit, n]] = total
                known: dict = {}
                for s in by_n[n]:
                    out[rows, at[s]] = score_spectra(c, v, ends, total, types, s, (models or {}).get(n), known)
    out[~np.isfinite(out)] = np.nan
    if any(isinstance(s, Ensemble) for s in settings):
        columns = []
        for s in settings:
            x = out[:, [at[m] for m in members(s)]]
            there = ~np.isnan(x)
            n = there.sum(axis=1)
            columns.append(np.where(n > 0, np.where(there, x, 0.0).sum(axis=1) / np.maximum(n, 1), np.nan))
        return totals, np.stack(columns, axis=1)
    return totals, out[:, [at[s] for s in settings]]


def specs_of(settings: Sequence[Setting | Ensemble]) -> list[tuple[str, int]]:
    return list(dict.fromkeys(m.spec for s in settings for m in members(s)))


def score_column(text: Column, settings: Sequence[Setting | Ensemble], models: Mapping[int, RankModel] | None = None) -> Column:
    """``struct<totals: array<bigint>, scores: array<double>>`` of a text: n-grams by spec, scores by setting (NULL where not valid).

    Marked as not deterministic, so that Spark evaluates it once a row and not again in each filter on it.
    """
    settings = list(settings)

    def run(texts: pa.Array) -> pa.Array:
        totals, scores = score_texts(texts.to_pylist(), settings, models)
        ends = lambda a: pa.array(np.arange(len(a) + 1, dtype=np.int32) * a.shape[1])
        values = pa.array(scores.ravel(), mask=np.isnan(scores).ravel())
        return pa.StructArray.from_arrays([pa.ListArray.from_arrays(ends(totals), pa.array(totals.ravel())), pa.ListArray.from_arrays(ends(scores), values)], ["totals", "scores"])

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return F.arrow_udf(run, "struct<totals: array<bigint>, scores: array<double>>").asNondeterministic()(text)


def with_scores(docs: DataFrame, settings: Mapping[str, Setting | Ensemble], text_col: str = "text", models: Mapping[int, RankModel] | None = None, totals: str | None = None) -> DataFrame:
    """``docs`` with one double column for each name in ``settings``; NULL where a text has no n-gram or a score no reference.

    Every row is scored on its own, whatever its id.  ``totals`` names a column for the number of n-grams of
    the first setting.  A name that ``docs`` has already is an error; its other columns come back unchanged.
    """
    require_columns(docs, text_col)
    new = [*settings, *([totals] if totals else [])]
    clash = {c.lower() for c in docs.columns} & {n.lower() for n in new}
    if clash or not settings:
        raise ValueError(f"score columns need new names; taken: {sorted(clash)}")
    held = "scored"
    while held.lower() in {c.lower() for c in (*docs.columns, *new)}:
        held = "_" + held
    rows = docs.withColumn(held, score_column(F.col(f"`{text_col}`"), list(settings.values()), models))
    scores = [F.get(F.col(f"{held}.scores"), i).alias(name) for i, name in enumerate(settings)]
    return rows.select(*[F.col(f"`{c}`") for c in docs.columns], *scores, *([F.get(F.col(f"{held}.totals"), 0).alias(totals)] if totals else []))


def score_documents(docs: DataFrame, settings: Setting | Ensemble | Sequence[Setting | Ensemble], models: Mapping[int, RankModel] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, signature, n_total, score, valid``: each text under each setting (``n_total`` of an ensemble: of its first member)."""
    settings = [settings] if isinstance(settings, (Setting, Ensemble)) else list(settings)
    require_columns(docs, id_col, text_col)
    specs = {spec: i for i, spec in enumerate(specs_of(settings))}
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), score_column(F.col(f"`{text_col}`"), settings, models).alias("x"))
    total, value = (lambda s: F.get("x.totals", specs[members(s)[0].spec])), (lambda i: F.get("x.scores", i))
    if len(settings) == 1:
        return rows.select("doc_id", F.lit(signature(settings[0])).alias("signature"), total(settings[0]).alias("n_total"), value(0).alias("score")).withColumn("valid", F.col("score").isNotNull())
    each = F.array(*[F.struct(F.lit(signature(s)).alias("signature"), total(s).alias("n_total"), value(i).alias("score")) for i, s in enumerate(settings)])
    return rows.select("doc_id", F.inline(each)).withColumn("valid", F.col("score").isNotNull())


def flat(batch: pa.RecordBatch, column: str = "spectrum") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(c, v, ends) of a batch's spectra."""
    lists = batch.column(column)
    ends = lists.offsets.to_numpy()
    entries = lists.values.slice(ends[0], ends[-1] - ends[0])
    return entries.field("c").to_numpy(), entries.field("v").to_numpy(), ends - ends[0]


def score(spectra: DataFrame, settings: Setting | Sequence[Setting], models: dict[int, RankModel] | None = None) -> DataFrame:
    """``doc_id, signature, n_total, score, valid``: each spectrum under each of the settings that ask for its unit and length.

    Texts without an n-gram, and scores without a reference, have a NULL score and are not valid.
    ``models`` gives expected ranks by n-gram length in place of the settings' own.
    """
    settings = [settings] if isinstance(settings, Setting) else list(settings)
    named = [(s, signature(s)) for s in settings]

    def run(batches):
        for b in batches:
            c, v, ends = flat(b)
            units, lengths = np.array(b.column("unit").to_pylist()), b.column("n").to_numpy()
            total, types = b.column("n_total").to_numpy(), b.column("n_types").to_numpy()
            for s, name in named:
                mine = np.flatnonzero((units == s.unit) & (lengths == s.n)) if len(units) else []
                if not len(mine):
                    continue
                take = np.concatenate([np.arange(ends[i], ends[i + 1]) for i in mine])
                cut = np.concatenate([[0], np.cumsum(ends[mine + 1] - ends[mine])])
                out = score_spectra(c[take], v[take], cut, total[mine], types[mine], s, (models or {}).get(s.n))
                bad = ~np.isfinite(out)
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id").take(pa.array(mine)), pa.array([name] * len(mine)), pa.array(total[mine]), pa.array(np.where(bad, 0.0, out), mask=bad), pa.array(~bad)],
                    ["doc_id", "signature", "n_total", "score", "valid"],
                )

    return spectra.select("doc_id", "unit", "n", "n_total", "n_types", "spectrum").mapInArrow(run, f"{id_field(spectra)}, signature string, n_total bigint, score double, valid boolean")


# --- the same in array functions -----------------------------------------------------------------------


def clip_eps(spectrum: Column, eps: float = 0, on: str = "count", n_total: Column | None = None) -> Column:
    """Entries whose count (or share of ``n_total``) is over ``eps``."""
    return F.filter(spectrum, lambda e: (e["c"] > eps) if on == "count" else (e["c"] > n_total * eps))


def clip_top(spectrum: Column, k: int | None = None) -> Column:
    """The ``k`` most frequent n-grams; an entry at the edge keeps what fits."""
    if k is None:
        return spectrum
    start = F.struct(F.lit(0).cast("bigint").alias("seen"), F.array().cast("array<struct<c: bigint, v: bigint>>").alias("kept"))
    step = lambda a, e: F.struct(
        (a["seen"] + e["v"]).alias("seen"),
        F.when(a["seen"] < k, F.concat(a["kept"], F.array(F.struct(e["c"].alias("c"), F.least(e["v"], k - a["seen"]).alias("v"))))).otherwise(a["kept"]).alias("kept"),
    )
    return F.aggregate(spectrum, start, step, lambda a: a["kept"])


def smooth(spectrum: Column, lam: float = 0.0) -> Column:
    """Entries ``c, v, p`` with additive smoothing of the kept n-grams, renormalised."""
    z = F.aggregate(spectrum, F.lit(0.0), lambda a, e: a + e["v"] * (e["c"] + F.lit(lam)))
    return F.element_at(F.transform(F.array(z), lambda t: F.transform(spectrum, lambda e: F.struct(e["c"].alias("c"), e["v"].alias("v"), ((e["c"] + F.lit(lam)) / t).alias("p")))), 1)


def distribution(s: Setting, spectrum: Column | None = None) -> Column:
    spectrum = F.col("spectrum") if spectrum is None else spectrum
    return smooth(clip_top(clip_eps(spectrum, s.eps, s.eps_on, F.col("n_total")), s.top_k), s.lam)


def length_column(s: Setting) -> Column:
    n = F.col("n_total").cast("double")
    if math.isinf(s.asymptote):
        return n
    a = F.lit(float(s.asymptote))
    return {"clamp": F.least(n, a), "hyperbolic": n * a / (n + a), "exponential": a * (1 - F.exp(-n / a))}[s.mode]


def distinct_share(df: DataFrame) -> DataFrame:
    """Spectra with ``distinct_share``: distinct n-grams over all n-grams; NULL where there is none."""
    return df.withColumn("distinct_share", F.try_divide(F.col("n_types"), F.col("n_total")))


def native_score(spectra: DataFrame, s: Setting, g: Callable[[Column], Column] | None = None, name: str = "score") -> DataFrame:
    """``spectra`` with a score column, for ``ttr``, ``moment`` and any nonlinearity ``g`` of one's own (then without length compensation)."""
    if s.metric == "ttr" and s.lam == 0 and s.eps == 0 and s.top_k is None:
        return spectra.withColumn(name, 1 - F.try_divide(F.col("n_types"), F.col("n_total")))
    if s.metric == "ttr":
        kept = clip_top(clip_eps(F.col("spectrum"), s.eps, s.eps_on, F.col("n_total")), s.top_k)
        types = F.aggregate(kept, F.lit(0.0), lambda a, e: a + e["v"])
        mass = F.aggregate(kept, F.lit(0.0), lambda a, e: a + e["v"] * (e["c"] + F.lit(s.lam)))
        return spectra.withColumn(name, F.when(F.col("n_total") > 0, F.coalesce(1 - F.try_divide(types, mass), F.lit(0.0))))
    if s.metric != "moment":
        raise ValueError("rank distances have no array form here; use score()")
    forms = {"pow": lambda p: F.pow(p, F.lit(s.k)), "entropy": lambda p: -p * F.ln(p), "sq_entropy": lambda p: F.pow(p * F.ln(p), F.lit(2.0))}
    form = g or forms[s.g]
    raw = F.aggregate(distribution(s), F.lit(0.0), lambda a, e: a + e["v"] * form(e["p"]))
    m = length_column(s)
    if g is not None or s.norm == "none":
        out = raw
    elif s.g == "entropy":
        out = 1 - F.try_divide(raw, F.ln(m))
    else:
        reference = F.pow(m, F.lit(1 - s.k)) if s.g == "pow" else F.pow(F.ln(m), F.lit(2.0)) / m
        out = raw - reference if s.norm == "difference" else F.try_divide(raw, reference)
    return spectra.withColumn(name, F.when(F.col("n_total") > 0, out))


def capped_ttr(docs: DataFrame, n: int = 6, most: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_total, score``: 1 - V/N over the first ``most`` character n-grams only, which makes long documents comparable."""
    first = spectra_of_docs(docs, [("char", n)], cap=most + n - 1, id_col=id_col, text_col=text_col)
    return native_score(first, Setting(metric="ttr", n=n, cap=most + n - 1)).select("doc_id", "n_total", "score")


def ensemble(scored: DataFrame, how: str = "mean", stats: DataFrame | None = None) -> DataFrame:
    """``doc_id, n_scores, score``: the mean of a document's valid scores over settings.

    With ``how="standardised"`` each is first put in standard deviations from its setting's mean,
    given by ``stats`` (``signature, mean, sd``; see ``score_stats``).
    """
    rows = scored.where("valid")
    value = F.col("score")
    if how == "standardised":
        rows = rows.join(F.broadcast(stats), "signature")
        value = F.try_divide(F.col("score") - F.col("mean"), F.col("sd"))
    elif how != "mean":
        raise ValueError(f"unknown way {how!r}")
    return rows.groupBy("doc_id").agg(F.count(value).alias("n_scores"), F.avg(value).alias("score"))


def score_stats(scored: DataFrame) -> DataFrame:
    return scored.where("valid").groupBy("signature").agg(F.avg("score").alias("mean"), F.stddev_samp("score").alias("sd"))


# --- expected ranks from data ---------------------------------------------------------------------------


def mean_rank_shares(spectra: DataFrame) -> DataFrame:
    """``n, rank, share``: the mean share of each rank over documents, in which absent ranks count 0."""
    clean = spectra.where("n_total > 0")
    runs = F.aggregate(
        "spectrum",
        F.array().cast("array<bigint>"),
        lambda a, e: F.concat(a, F.array_repeat(e["c"], e["v"].cast("int"))),
    )
    shares_of = clean.select("n", "n_total", F.posexplode(runs).alias("at", "c"))
    sums = shares_of.groupBy("n", (F.col("at") + 1).alias("rank")).agg(F.sum(F.col("c") / F.col("n_total")).alias("total"))
    docs = clean.groupBy("n").agg(F.count(F.lit(1)).alias("docs"))
    return sums.join(F.broadcast(docs), "n").select("n", F.col("rank").cast("bigint").alias("rank"), (F.col("total") / F.col("docs")).alias("share"))


def rank_steps(spectra: DataFrame) -> DataFrame:
    """``n, rank, step``: by how much the documents' shares, added up, fall behind a rank; at rank 0, how many documents there are.

    A spectrum's entry is one step, however many n-grams it stands for.
    """

    def run(batches):
        for b in batches:
            c, v, ends = flat(b)
            lengths, total = b.column("n").to_numpy(), b.column("n_total").to_numpy()
            size = np.diff(ends)
            doc = np.repeat(np.arange(len(size)), size)
            seen = np.concatenate([[0], np.cumsum(v)])
            rank = seen[1:] - seen[ends[:-1]][doc]
            after = np.append(c[1:], 0) if len(c) else c
            after[ends[1:][size > 0] - 1] = 0
            step = (c - after) / np.maximum(total, 1)[doc]
            for n in np.unique(lengths).tolist():
                mine = (lengths == n) & (total > 0)
                here = mine[doc]
                ranks, at = np.unique(rank[here], return_inverse=True)
                steps = np.bincount(at, weights=step[here], minlength=len(ranks))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ranks) + 1, n, np.int32)), pa.array(np.append(0, ranks)), pa.array(np.append(float(mine.sum()), steps))], ["n", "rank", "step"])

    return spectra.select("n", "n_total", "spectrum").mapInArrow(run, "n int, rank bigint, step double").groupBy("n", "rank").agg(F.sum("step").alias("step"))


def empirical_models(spectra: DataFrame) -> dict[int, RankModel]:
    """Rank models by n-gram length from clean documents: the mean share of every rank that any of them has.

    The driver takes ranks at which shares fall, not ranks: far out, where few documents reach, there are few of them.
    """
    rows = rank_steps(spectra).toArrow()
    n, rank, step = (rows.column(c).to_numpy() for c in ("n", "rank", "step"))
    out = {}
    for length in np.unique(n).tolist():
        order = np.flatnonzero(n == length)
        order = order[np.argsort(rank[order])]
        docs, ends, falls = step[order[0]], rank[order[1:]], step[order[1:]]
        if docs > 0:  # sums from the last rank on, the smallest first
            out[length] = RankModel(shares=np.cumsum(falls[::-1])[::-1] / docs, ends=ends)
    return out


def fit_rank_model(spectra: DataFrame) -> DataFrame:
    """``n, n_ranks, exponent, intercept, r2``: least squares of ln share on ln rank."""
    pts = mean_rank_shares(spectra).select("n", F.ln("share").alias("y"), F.ln("rank").alias("x"))
    return pts.groupBy("n").agg(F.count(F.lit(1)).alias("n_ranks"), (-F.regr_slope("y", "x")).alias("exponent"), F.regr_intercept("y", "x").alias("intercept"), F.regr_r2("y", "x").alias("r2"))
