"""Toxicity by multiple-instance learning.

Labels exist for documents, not sentences.  Every sentence gets a probability from a
logistic model over its words and word prefixes; a document is toxic unless all its
sentences are clean (noisy-or), and the model is trained through that rule, so it
learns which sentences are to blame.  Training runs on a bounded sample of labelled
documents; scoring is one narrow pass over every text.
"""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import Memo, fresh, labelled_sample, offsets

SENTENCE = re.compile(r"[^.!?\n]+[.!?]*")
WORD = re.compile(r"\w+")
PREFIXES = (3, 4, 5, 6)
SCHEMA = "doc_id bigint, doc_score double, sentence_no int, span_start int, span_end int, sentence_score double, sentence string"


def word_features(word: str) -> list[str]:
    """The word itself and its beginnings, which gather inflected and compounded forms."""
    return ["=" + word, *("^" + word[:n] for n in PREFIXES if n < len(word))]


@dataclass
class Model:
    """Sentence log-odds: ``bias`` plus the weight of each feature that occurs in it, once each."""

    weights: dict[str, float]
    bias: float
    threshold: float = 0.5
    held_out: dict = field(default_factory=dict)

    def spans(self, text: str, known: Memo) -> tuple[float, list[tuple[int, int, int, float]]]:
        """(document probability, (number, start, end, probability) of each sentence that has a word with a feature).

        Sentences without evidence say nothing: counting their base rate would condemn every long text.
        """
        out, clean = [], 1.0
        for no, m in enumerate(SENTENCE.finditer(text)):
            found: dict[str, float] = {}
            for w in WORD.findall(m.group().lower()):
                if (f := known[w]) is not None:
                    found.update(f)
            if found:
                p = 1.0 / (1.0 + np.exp(-(self.bias + sum(found.values()))))
                clean *= 1.0 - p
                out.append((no, m.start(), m.end(), float(p)))
        return 1.0 - clean, out

    def memo(self) -> Memo:
        def look(word):
            hit = {f: w for f in word_features(word) if (w := self.weights.get(f)) is not None}
            return hit or None

        return Memo(look)


def _candidates(sentences: list[list[set[str]]], y: np.ndarray, z: float = 4.0) -> dict[str, int]:
    """Features whose share among toxic documents exceeds that among clean ones by ``z`` standard errors."""
    tally: tuple[dict[str, int], dict[str, int]] = ({}, {})
    for doc, label in zip(sentences, y):
        seen = {f for w in set().union(*doc) for f in word_features(w)} if doc else ()
        into = tally[int(label)]
        for f in seen:
            into[f] = into.get(f, 0) + 1
    n0, n1 = np.maximum(np.bincount(y, minlength=2), 1)
    names = list(tally[1])
    k, c = np.array([tally[1][f] for f in names]), np.array([tally[0].get(f, 0) for f in names])
    p = (k + c) / (n0 + n1)
    good = k / n1 - c / n0 > z * np.sqrt(p * (1 - p) * (1 / n0 + 1 / n1))
    return {f: i for i, f in enumerate(sorted(itertools.compress(names, good)))}


def loss(theta: np.ndarray, flat, starts, row, owner, y, weight, decay: float) -> tuple[float, np.ndarray]:
    """(negative log likelihood of the documents' labels under noisy-or with a penalty on weights, its gradient).

    ``flat`` has the features of all sentences, which begin at ``starts``; ``row`` is the sentence of each, ``owner`` the
    document of each sentence; the last of ``theta`` is the bias.
    """
    z = np.clip(np.add.reduceat(theta[flat], starts) + theta[-1], -30, 30)
    log_clean = -np.logaddexp(0, z)  # log(1 - p) of each sentence
    total = np.minimum(np.bincount(owner, weights=log_clean, minlength=len(y)), -1e-12)
    clean = np.exp(total)
    value = -(weight * np.where(y == 1, np.log(np.maximum(1 - clean, 1e-12)), total)).sum() / len(y) + decay / 2 * (theta[:-1] ** 2).sum()
    # d value / d z = p where the document is clean, -p * clean / (1 - clean) where it is toxic
    slope = np.where(y == 1, -clean / np.maximum(1 - clean, 1e-9), 1.0) * weight
    g_z = slope[owner] / (1 + np.exp(-z))
    g = np.append(np.bincount(flat, weights=g_z[row], minlength=len(theta) - 1), g_z.sum()) / len(y)
    g[:-1] += decay * theta[:-1]
    return float(value), g


def fit(texts: list[str], toxic: list[int], epochs: int = 300, rate: float = 0.1, decay: float = 2e-4) -> Model:
    """Noisy-or maximum likelihood by Adam; classes weigh the same, whatever their sizes.

    With no toxic or no clean document there is nothing to tell apart: the model then finds none.
    """
    y = np.asarray(toxic, dtype=np.int64)
    if not len(y) or y.min() == y.max():
        return Model({}, -20.0)
    docs = [[set(WORD.findall(s.lower())) for s in SENTENCE.findall(t)] for t in texts]
    index = _candidates(docs, y)
    if not index:
        return Model({}, -20.0)
    known = Memo(lambda w: [index[f] for f in word_features(w) if f in index])
    cols, ends, owner = [], [], []
    for d, doc in enumerate(docs):
        for s in doc:
            if f := set(itertools.chain.from_iterable(known[w] for w in s)):
                cols.append(np.fromiter(f, dtype=np.int64))
                ends.append(len(f))
                owner.append(d)
    flat, starts, owner = np.concatenate(cols), offsets(ends)[:-1], np.asarray(owner)
    row = np.repeat(np.arange(len(ends)), ends)
    weight = (0.5 / np.maximum(np.bincount(y, minlength=2), 1))[y] * len(y)
    theta = np.zeros(len(index) + 1)
    theta[-1] = -4.0
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for t in range(1, epochs + 1):
        _, g = loss(theta, flat, starts, row, owner, y, weight, decay)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        theta -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return Model({f: float(theta[i]) for f, i in index.items() if abs(theta[i]) > 1e-4}, float(theta[-1]))


def probability(model: Model, texts: list[str]) -> np.ndarray:
    known = model.memo()
    return np.array([model.spans(t, known)[0] for t in texts])


def train(docs: DataFrame, labels: DataFrame, max_docs: int = 4000, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """A model from at most ``max_docs`` labelled documents, whole texts: half toxic ones where there are as many (``labelled_sample``).

    A fifth of the sample is held out; the threshold is the score midway between the toxic and clean of that
    part if they part, else the one that errs least, each class weighing the same.
    """
    rows = labelled_sample(docs, labels, "toxic", max_docs // 2, id_col, text_col)
    texts, target = [], []
    for r in rows.toLocalIterator():
        texts.append(r["text"])
        target.append(int(r["y"]))
    held = [i for i in range(len(texts)) if i % 5 == 4]
    part = set(held)
    model = fit([t for i, t in enumerate(texts) if i not in part], [t for i, t in enumerate(target) if i not in part])
    p, q = probability(model, [texts[i] for i in held]), np.array([target[i] for i in held], dtype=int)
    if len(q) and q.min() != q.max():
        cuts = np.unique(np.concatenate([[0.5], (np.sort(p)[1:] + np.sort(p)[:-1]) / 2]))
        cost = [((p <= c) & (q == 1)).sum() / (q == 1).sum() + ((p > c) & (q == 0)).sum() / (q == 0).sum() for c in cuts]
        best = cuts[np.flatnonzero(np.isclose(cost, min(cost)))]
        model.threshold = float(np.clip(best[np.abs(best - 0.5).argmin()], 0.05, 0.95))
        model.held_out = {"documents": len(q), "recall": float((p[q == 1] > model.threshold).mean()), "false_alarms": float((p[q == 0] > model.threshold).mean())}
    return model


def offending_sentences(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per offending sentence of each document whose noisy-or score is over the threshold.

    ``span_start, span_end`` count code points from 0.  Offending are the sentences over the
    threshold themselves, or the highest one if only all together pass it.  Clean
    documents, NULL and empty texts give no rows; rows with NULL or repeated ids are
    judged like any other.  Texts are read whole.  An empty table gives no rows.  Other columns, whatever their names, are ignored.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).where("text IS NOT NULL")

    def run(batches):
        known = model.memo()
        for b in batches:
            out: list[tuple] = []
            for key, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                score, spans = model.spans(text, known)
                if score > model.threshold:
                    bar = min(model.threshold, max(s[3] for s in spans) * (1 - 1e-12))
                    out += [(key, score, no, s, e, p, text[s:e]) for no, s, e, p in spans if p > bar]
            if out:
                types = [pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(zip(*out), types)], ["doc_id", "doc_score", "sentence_no", "span_start", "span_end", "sentence_score", "sentence"])

    return rows.mapInArrow(run, SCHEMA)


def with_score(docs: DataFrame, model: Model, name: str = "toxicity", text_col: str = "text") -> DataFrame:
    """``docs`` with the noisy-or score of each text; 0 for texts that are NULL or empty. Each text is judged once, whatever uses the column."""

    @F.pandas_udf("double")
    def score(texts):
        known = model.memo()
        return texts.map(lambda t: float(model.spans(t, known)[0]) if t else 0.0)

    return docs.withColumn(name, score.asNondeterministic()(F.col(f"`{text_col}`")))


def drop_toxic(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose score is not over the threshold.

    NULL and empty texts stay; texts of any length are read whole; NULL and repeated ids play no part, each row is
    judged by its text; an empty table gives an empty table.  Columns come back unchanged, whatever their names.
    """
    (name,) = fresh(docs, "toxicity")
    return with_score(docs, model, name, text_col).where(F.col(name) <= model.threshold).select(*[F.col(f"`{c}`") for c in docs.columns])
