"""Quality rules learnt by gradient-boosted trees over document statistics.

Statistics are counts over characters, words and lines that fit any text: shares of kinds of
characters, entropy, repetition of words, word pairs and lines, lengths and their spread.  All texts of a batch are
counted at once in numpy.  Every labelled document is learnt from: tasks put its statistics into bins, a byte each, and only these
bytes meet where trees are grown.  Trees are grown on binned statistics by second-order boosting, with
signs that a split must respect on chosen statistics (more symbols, capitals or repetition
never raise the score).  A model is a set of flat numpy node arrays; scoring moves all rows of a
batch down one level at a time, with no branching per row.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import cut_lineage, fresh, kept, mix64
from textredun.operators import kernel

#: statistic -> sign of its effect on the score (0: free)
STATISTICS = {
    "log_chars": 0,
    "log_words": 0,
    "mean_word": 0,
    "word_spread": 0,
    "long_words": 0,
    "short_words": 0,
    "bare_words": -1,  # without a letter
    "marked_words": -1,  # with a symbol
    "stutter": -1,  # like the word before
    "top_word": -1,
    "distinct_words": 0,
    "repeated_pairs": -1,
    "symbols": -1,
    "doubled_marks": -1,
    "punctuation": 0,
    "digits": 0,
    "capitals": -1,
    "blanks": 0,
    "entropy": 0,
    "mean_line": 0,
    "line_spread": 0,
    "repeated_lines": -1,
}
SIGNS = np.array(list(STATISTICS.values()))
LETTER, DIGIT, CAPITAL, BLANK, MARK, SYMBOL = 1, 2, 4, 8, 16, 32
PLAIN_MARKS = ".,;:!?'\"()-"


def kind_of(c: str) -> int:
    """Bits for what a character is: letters (capitals too), digits, blanks, marks of plain prose, other symbols."""
    if c.isspace():
        return BLANK
    if c in PLAIN_MARKS or unicodedata.category(c) in ("Pd", "Pi", "Pf"):
        return MARK
    k = unicodedata.category(c)
    if k[0] == "L":
        return LETTER | (CAPITAL if k == "Lu" else 0)
    return LETTER if k[0] == "M" else DIGIT if k[0] == "N" else SYMBOL


def _kinds() -> np.ndarray:
    """``kind_of`` of the first 65,536 code points, and of all others by their plane: symbols in the second, letters elsewhere."""
    return np.array([kind_of(chr(i)) for i in range(1 << 16)] + [SYMBOL, LETTER], dtype=np.uint8)


def _sums(flags: np.ndarray, ends: np.ndarray) -> np.ndarray:
    if len(ends) == 2:
        return np.array([np.count_nonzero(flags)])
    run = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
    return run[ends[1:]] - run[ends[:-1]]


def _repeats(hashes: np.ndarray, owner: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct hashes, count of the most frequent one) of each of n owners."""
    key = np.sort(mix64(hashes + mix64(owner.astype(np.uint64))) >> np.uint64(20) | owner.astype(np.uint64) << np.uint64(44))
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, dtype=np.int64)
    of = (key[first] >> np.uint64(44)).astype(np.int64)
    top = np.zeros(n, dtype=np.int64)
    np.maximum.at(top, of, np.diff(np.append(first, len(key))))
    return np.bincount(of, minlength=n), top


BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)


STEP = 1 << 18  # characters hashed at a time


def _powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of ``BASE`` and of its inverse, modulo 2**64, up to ``STEP``."""
    held = []
    for x in (BASE, INVERSE):
        steps = np.full(STEP + 1, x, dtype=np.uint64)
        steps[0] = 1
        held.append(np.cumprod(steps, dtype=np.uint64))
    return held[0], held[1]


def _hashes(codes: np.ndarray):
    """A function of (starts, ends) that gives 64-bit hashes of stretches: a polynomial in ``BASE``, from one running sum over all characters."""
    powers, inverse = kept("powers", _powers)
    mixed = kept("character hashes", lambda: mix64(np.arange(1, 0x110001, dtype=np.uint64)))
    far, back = (np.cumprod(np.array([1] + [x[STEP]] * (len(codes) // STEP), dtype=np.uint64), dtype=np.uint64) for x in (powers, inverse))
    run = np.empty(len(codes) + 1, dtype=np.uint64)
    run[0] = 0
    for i, at in enumerate(range(0, len(codes), STEP)):
        some = codes[at : at + STEP]
        np.cumsum(mixed[some] * (powers[: len(some)] * far[i]), out=run[at + 1 : at + 1 + len(some)])
        run[at + 1 : at + 1 + len(some)] += run[at]
    return lambda a, b: (run[b] - run[a]) * (inverse[a % STEP] * back[a // STEP])


def _spread(lengths: np.ndarray, owner: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(mean, standard deviation over mean) of the lengths of each owner."""
    n = len(count)
    mean = np.bincount(owner, weights=lengths, minlength=n) / np.maximum(count, 1)
    square = np.bincount(owner, weights=np.square(lengths, dtype=np.float64), minlength=n) / np.maximum(count, 1)
    return mean, np.sqrt(np.maximum(square - mean * mean, 0)) / np.maximum(mean, 1e-9)


def _statistics(texts: list[str]) -> np.ndarray:
    codes, ends = kernel.code_points(texts)
    n, size = len(texts), np.diff(ends)
    if n == 1:  # a text of any length
        codes = codes.astype(np.int32)
    owner = np.repeat(np.arange(n), size) if n > 1 else np.zeros(len(codes), dtype=np.int8)
    out = np.zeros((n, len(STATISTICS)))
    put = lambda name, x: out.__setitem__((slice(None), list(STATISTICS).index(name)), x)
    table = kept("character kinds", _kinds)
    kind = table[np.where(codes < 1 << 16, codes, np.where(codes < 1 << 17, 1 << 16, (1 << 16) + 1))]
    blank = (kind & BLANK) > 0
    starts_text = np.zeros(len(codes) + 1, dtype=bool)
    starts_text[ends[:-1]] = True
    starts_text = starts_text[:-1]
    before = np.concatenate([[True], blank[:-1]]) if len(codes) else blank
    begin = np.flatnonzero(~blank & (before | starts_text))
    # a word ends before a blank, a new text, or the end of all
    stop = np.flatnonzero(~blank & (np.concatenate([blank[1:], [True]]) | np.concatenate([starts_text[1:], [True]]))) + 1 if len(codes) else begin
    of_word = owner[begin]
    long = stop - begin
    words = np.bincount(of_word, minlength=n)
    w, c = np.maximum(words, 1), np.maximum(size, 1)
    put("log_chars", np.log1p(size))
    put("log_words", np.log1p(words))
    mean, spread = _spread(long, of_word, words)
    put("mean_word", mean)
    put("word_spread", spread)
    put("long_words", np.bincount(of_word[long > 15], minlength=n) / w)
    put("short_words", np.bincount(of_word[long < 4], minlength=n) / w)
    within = lambda flag, a, b: (lambda run: run[b] - run[a])(np.concatenate([np.zeros(1, dtype=np.int32), np.cumsum(flag, dtype=np.int32)]))
    symbol, letter = (kind & SYMBOL) > 0, (kind & LETTER) > 0
    put("bare_words", np.bincount(of_word[within(letter, begin, stop) == 0], minlength=n) / w)
    put("marked_words", np.bincount(of_word[within(symbol, begin, stop) > 0], minlength=n) / w)
    hashes = _hashes(codes)
    word = hashes(begin, stop)
    same_text = of_word[1:] == of_word[:-1]
    put("stutter", np.bincount(of_word[1:][same_text & (word[1:] == word[:-1])], minlength=n) / w)
    distinct, top = _repeats(word, of_word, n)
    put("top_word", top / w)
    put("distinct_words", distinct / w**0.8)
    pairs = (mix64(word[:-1]) + word[1:])[same_text]
    distinct, _ = _repeats(pairs, of_word[1:][same_text], n)
    put("repeated_pairs", np.where(words > 1, 1 - distinct / np.maximum(words - 1, 1), 0.0))
    mark = (kind & (MARK | SYMBOL)) > 0
    put("symbols", _sums(symbol, ends) / c)
    put("doubled_marks", _sums(mark & np.concatenate([[False], codes[1:] == codes[:-1]]) & ~starts_text if len(codes) else mark, ends) / w)
    put("punctuation", _sums((kind & MARK) > 0, ends) / c)
    put("digits", _sums((kind & DIGIT) > 0, ends) / c)
    put("capitals", _sums((kind & CAPITAL) > 0, ends) / c)
    put("blanks", _sums(blank, ends) / c)
    if n == 1:
        times = sum(np.bincount(codes[at : at + STEP], minlength=0x110000) for at in range(0, max(len(codes), 1), STEP))
        times = times[times > 0]
        of = np.zeros(len(times), dtype=np.int64)
    else:
        ordered = np.sort(owner << 21 | codes)
        first = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(ordered) else np.zeros(0, dtype=np.int64)
        times, of = np.diff(np.append(first, len(ordered))), ordered[first] >> 21
    put("entropy", np.where(size > 0, np.log(c) - np.bincount(of, weights=times * np.log(times), minlength=n) / c, 0.0))
    line_end = codes == 10
    at = np.flatnonzero(line_end | np.concatenate([starts_text[1:], [True]])) if len(codes) else np.zeros(0, dtype=np.int64)
    # lines run from behind the last end to the next one; empty ones don't count
    to = at + ~line_end[at]
    since = np.maximum(np.concatenate([[0], at[:-1] + 1]), 0) if len(at) else at
    full = to > since
    to, since = to[full], since[full]
    of_line = owner[since] if len(since) else since
    lines = np.bincount(of_line, minlength=n)
    mean, spread = _spread(to - since, of_line, lines)
    put("mean_line", mean)
    put("line_spread", spread)
    distinct, _ = _repeats(hashes(since, to), of_line, n)
    put("repeated_lines", np.where(lines > 0, 1 - distinct / np.maximum(lines, 1), 0.0))
    return out


def statistics_of(texts: list[str]) -> np.ndarray:
    """The statistics of texts, one row each, in the order of ``STATISTICS``; an empty text has 0 in all."""
    parts = [_statistics(some) for _, some in kernel.slices(texts, rows=200, chars=150_000)]
    return np.concatenate(parts) if parts else np.zeros((0, len(STATISTICS)))


@dataclass
class Trees:
    """Complete binary trees of one depth as node arrays: node i has children 2i+1 and 2i+2; a dead split sends all rows left."""

    feature: np.ndarray  # [tree, inner node] int
    cut: np.ndarray  # [tree, inner node]; rows with value > cut go right
    leaf: np.ndarray  # [tree, leaf] log-odds
    base: float
    threshold: float = 0.0
    held_out: dict = field(default_factory=dict)

    def score(self, x: np.ndarray) -> np.ndarray:
        """Log-odds of good quality of each row of statistics."""
        out = np.full(len(x), self.base)
        rows, depth = np.arange(len(x)), int(np.log2(self.leaf.shape[1])) if len(self.leaf) else 0
        for feature, cut, leaf in zip(self.feature, self.cut, self.leaf):
            node = np.zeros(len(x), dtype=np.int64)
            for _ in range(depth):
                node = 2 * node + 1 + (x[rows, feature[node]] > cut[node])
            out += leaf[node - len(feature)]
        return out


def grow(code: np.ndarray, y: np.ndarray, signs: np.ndarray = SIGNS, n_trees: int = 60, depth: int = 4, rate: float = 0.2, l2: float = 1.0, least: float = 1e-3) -> Trees:
    """Logistic boosting with monotone signs on bins ``code[statistic, row]``; the two classes weigh the same. The cuts are bins.

    A split on a signed statistic is refused if its sides are in the wrong order, and
    bounds the leaves under it at the middle of the sides, so the whole tree keeps the order.
    """
    k, n = code.shape
    y = y.astype(float)
    inner, leaves = (1 << depth) - 1, 1 << depth
    if not n or y.min() == y.max():
        return Trees(np.zeros((0, inner), int), np.zeros((0, inner)), np.zeros((0, leaves)), 5.0 if not n or y.min() == 1 else -5.0)
    weight = np.where(y == 1, 0.5 / y.sum(), 0.5 / (n - y.sum())) * n
    width = int(code.max()) + 2
    f = np.zeros(n)
    trees = []
    for _ in range(n_trees):
        p = 1 / (1 + np.exp(-f))
        g, h = weight * (y - p), weight * p * (1 - p)
        feature, cut, leaf = np.zeros(inner, int), np.full(inner, np.inf), np.zeros(leaves)
        node = np.zeros(n, dtype=np.int64)
        low, high = np.full(inner + leaves, -np.inf), np.full(inner + leaves, np.inf)
        for at in range(inner):
            mine = np.flatnonzero(node == at)
            left, right = 2 * at + 1, 2 * at + 2
            low[left] = low[right] = low[at]
            high[left] = high[right] = high[at]
            if len(mine) >= 2:
                g_mine, h_mine = g[mine], h[mine]
                gs, hs = np.empty((k, width)), np.empty((k, width))
                for j in range(k):
                    bins = code[j][mine].astype(np.intp)
                    gs[j], hs[j] = np.bincount(bins, g_mine, width), np.bincount(bins, h_mine, width)
                gs, hs = gs.cumsum(1), hs.cumsum(1)
                gl, hl = gs[:, :-1], hs[:, :-1]
                gr, hr = gs[:, -1:] - gl, hs[:, -1:] - hl
                vl, vr = np.clip(gl / (hl + l2), low[at], high[at]), np.clip(gr / (hr + l2), low[at], high[at])
                gain = gl * gl / (hl + l2) + gr * gr / (hr + l2) - gs[:, -1:] ** 2 / (hs[:, -1:] + l2)
                gain[(hl < least * n) | (hr < least * n) | ((vr - vl) * signs[:, None] < 0)] = -np.inf
                j, b = np.unravel_index(gain.argmax(), gain.shape)
                if gain[j, b] > 1e-6:
                    feature[at], cut[at] = j, b
                    if signs[j]:
                        middle = (vl[j, b] + vr[j, b]) / 2
                        (high if signs[j] > 0 else low)[left] = middle
                        (low if signs[j] > 0 else high)[right] = middle
            node[mine] = left + (code[feature[at]][mine] > cut[at])
        where = node - inner
        gsum, hsum = np.bincount(where, g, leaves), np.bincount(where, h, leaves)
        leaf = rate * np.clip(gsum / (hsum + l2), low[inner:], high[inner:])
        leaf[hsum == 0] = rate * np.clip(0.0, low[inner:], high[inner:])[hsum == 0]
        f += leaf[where]
        trees.append((feature, cut, leaf))
    return Trees(*(np.stack(a) for a in zip(*trees)), 0.0)


def binned(x: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    """[statistic, row] bins: how many of a statistic's edges lie below the value."""
    return np.stack([np.searchsorted(e, x[:, j], side="left").astype(np.uint8) for j, e in enumerate(edges)])


def at_edges(trees: Trees, edges: list[np.ndarray]) -> Trees:
    """The trees with edges in place of bins as cuts."""
    cut = np.array([[edges[j][int(b)] if np.isfinite(b) else np.inf for j, b in zip(*row)] for row in zip(trees.feature, trees.cut)]).reshape(trees.cut.shape)
    return Trees(trees.feature, cut, trees.leaf, trees.base, trees.threshold, trees.held_out)


def fit(x: np.ndarray, y: np.ndarray, signs: np.ndarray = SIGNS, bins: int = 64, **how) -> Trees:
    """``grow`` on rows of statistics, with their quantiles as edges of at most 256 bins."""
    if not len(x):
        return grow(np.zeros((x.shape[1], 0), dtype=np.uint8), y, signs, **how)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(x.shape[1])]
    return at_edges(grow(binned(x, edges), y, signs, **how), edges)


FINE = np.int64(40)  # bits of a double that its slot leaves out; 12 of its fraction stay


def slots(x: np.ndarray) -> np.ndarray:
    """Integers in the order of the values; those that differ by less than 1 in 4096 may share one."""
    raw = np.ascontiguousarray(x, dtype=np.float64).view(np.int64)
    size = (raw & np.int64(0x7FFFFFFFFFFFFFFF)) >> FINE
    return np.where(raw < 0, -size, size)


def slot_ends(slot: np.ndarray) -> np.ndarray:
    """The largest value of each slot."""
    size = np.abs(slot.astype(np.int64))
    return np.where(slot < 0, -(size << FINE).view(np.float64), (((size + 1) << FINE) - 1).view(np.float64))


def quantile_edges(slot: np.ndarray, count: np.ndarray, bins: int = 64) -> np.ndarray:
    """Edges that part values, counted by slot in order, into bins of equal weight as far as slots allow."""
    below = np.cumsum(count)
    return slot_ends(np.unique(slot[np.searchsorted(below, below[-1] * np.arange(1, bins) / bins)]))


def with_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id`` and the statistics of each text that is not NULL."""
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).where("text IS NOT NULL")

    def run(batches):
        for b in batches:
            x = statistics_of(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, x.T)], ["doc_id", *STATISTICS])

    return rows.mapInArrow(run, "doc_id bigint, " + ", ".join(f"{c} double" for c in STATISTICS))


def threshold_for(good: np.ndarray, bad: np.ndarray, keep: float = 0.999, pass_bad: float = 0.05) -> float:
    """Midway between the classes if they part.  Else even odds, lowered until the share ``keep`` of the good passes, but not so far that more than ``pass_bad`` of the bad do."""
    if not len(good) or not len(bad):
        return 0.0
    if bad.max() < good.min():
        return float((bad.max() + good.min()) / 2)
    lowest = min(0.0, float(np.quantile(good, 1 - keep, method="lower")))
    return float(min(0.0, max(lowest, np.nextafter(np.quantile(bad, 1 - pass_bad, method="higher"), np.inf))))


def labelled_statistics(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``h, y`` and the statistics of every document with a label of 0 or 1; ``h`` is a hash of its id.

    Of an id's labels the greatest counts, of its texts that with the least hash. NULL labels, ids and texts are left out.
    Texts are judged where they lie; only their statistics are shuffled.
    """
    y = labels.select("doc_id", F.col("quality").cast("int").alias("y")).where("y IN (0, 1) AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("y").alias("y"))
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).where("doc_id IS NOT NULL AND text IS NOT NULL").withColumn("digest", F.xxhash64("text"))

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("digest"), *map(pa.array, statistics_of(b.column("text").to_pylist()).T)], ["doc_id", "digest", *STATISTICS])

    kind = rows.schema["doc_id"].dataType.simpleString()
    seen = rows.mapInArrow(run, f"doc_id {kind}, digest bigint, " + ", ".join(f"{c} double" for c in STATISTICS))
    one = seen.join(y, "doc_id").groupBy("doc_id").agg(F.max("y").alias("y"), F.min(F.struct("digest", *STATISTICS)).alias("x"))
    return one.select(F.xxhash64("doc_id").alias("h"), "y", *[F.col(f"x.{c}").alias(c) for c in STATISTICS])


def edges_of(known: DataFrame, bins: int = 64) -> list[np.ndarray]:
    """Edges of each statistic's bins, from the counts of all rows by slot."""

    def run(batches):
        held = [np.stack([b.column(c).to_numpy() for c in STATISTICS]) for b in batches if b.num_rows]
        for j in range(len(STATISTICS) if held else 0):
            slot, n = np.unique(slots(np.concatenate([x[j] for x in held])), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(slot), j, dtype=np.int32)), pa.array(slot), pa.array(n)], ["statistic", "slot", "n"])

    got = known.select(*STATISTICS).mapInArrow(run, "statistic int, slot bigint, n bigint").groupBy("statistic", "slot").agg(F.sum("n").alias("n")).toArrow().sort_by([("statistic", "ascending"), ("slot", "ascending")])
    of, slot, n = (got.column(c).to_numpy() for c in ("statistic", "slot", "n"))
    return [quantile_edges(slot[of == j], n[of == j], bins) for j in range(len(STATISTICS))] if len(of) else []


def train(docs: DataFrame, labels: DataFrame, keep: float = 0.999, pass_bad: float = 0.05, folds: int = 3, id_col: str = "doc_id", text_col: str = "text") -> Trees:
    """Trees from all labelled documents (``labelled_statistics``).

    Every document is also judged by trees that haven't seen it (``folds`` parts); the threshold comes
    from these judgements (``threshold_for``), and ``held_out`` says what share of the good it keeps and of the bad it
    drops.  Without documents of both classes everything is kept, or nothing if all are bad.

    The trees of each part, and of all, are grown in a task of their own, to which a document sends 31 bytes and from which
    its score of 8 bytes comes back.
    """
    known = cut_lineage(labelled_statistics(docs, labels, id_col, text_col))
    edges = edges_of(known)
    if not edges:
        return fit(np.zeros((0, len(STATISTICS))), np.zeros(0))

    def pack(batches):
        for b in batches:
            code = binned(np.stack([b.column(c).to_numpy() for c in STATISTICS], axis=1), edges)
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in (b.column("h").to_numpy(), b.column("y").to_numpy().astype(np.uint8), code)], ["h", "y", "code"])

    def one(group: pa.Table) -> pa.Table:
        """The trees that leave out a part, and its scores; of the last model, the trees of all."""
        join = lambda c, kind: np.concatenate([np.frombuffer(x.as_buffer(), dtype=kind) for x in group.column(c)])
        part = group.column("part")[0].as_py()
        h, y = join("h", np.int64), join("y", np.uint8)
        code = np.concatenate([np.frombuffer(x.as_buffer(), dtype=np.uint8).reshape(len(edges), -1) for x in group.column("code")], axis=1)
        order = np.lexsort((code[0], y, h))  # sums don't hang on how rows were dealt out
        h, y, code = h[order], y[order], code[:, order]
        mine = h % folds == part
        trees = grow(code[:, ~mine], y[~mine])
        s = trees.score(code[:, mine].T)
        out = (trees.feature.astype(np.int64), trees.cut, trees.leaf, np.array([trees.base]), s[y[mine] == 1], s[y[mine] == 0])
        return pa.table([pa.array([part], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in out)], names=["part", "feature", "cut", "leaf", "base", "good", "bad"])

    blobs = known.mapInArrow(pack, "h binary, y binary, code binary").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(folds))))
    done = blobs.repartition(8 * (folds + 1), "part").groupBy("part").applyInArrow(one, "part int, feature binary, cut binary, leaf binary, base binary, good binary, bad binary").collect()
    whole = next(r for r in done if r["part"] == folds)
    leaf = np.frombuffer(whole["leaf"])
    shape = (-1, 15)
    trees = at_edges(Trees(np.frombuffer(whole["feature"], dtype=np.int64).reshape(shape), np.frombuffer(whole["cut"]).reshape(shape), leaf.reshape(-1, 16), float(np.frombuffer(whole["base"])[0])), edges)
    good, bad = (np.concatenate([np.frombuffer(r[c]) for r in done if r["part"] < folds]) for c in ("good", "bad"))
    if len(good) and len(bad):
        trees.threshold = threshold_for(good, bad, keep, pass_bad)
        trees.held_out = {"documents": len(good) + len(bad), "kept_good": float((good >= trees.threshold).mean()), "dropped_bad": float((bad < trees.threshold).mean())}
    return trees


def with_quality(docs: DataFrame, trees: Trees, name: str = "quality_score", text_col: str = "text") -> DataFrame:
    """``docs`` with the log-odds of good quality; NULL for NULL texts. Each text is judged once, whatever uses the column."""

    @F.pandas_udf("double")
    def score(texts):
        there = texts.notna().to_numpy()
        out = np.full(len(texts), np.nan)
        if there.any():
            out[there] = trees.score(statistics_of(texts[there].tolist()))
        return texts.__class__(out)

    text = F.col(f"`{text_col}`")
    return docs.withColumn(name, score.asNondeterministic()(text)).withColumn(name, F.when(text.isNotNull(), F.col(name)))


def quality_filter(docs: DataFrame, trees: Trees, text_col: str = "text", name: str | None = None) -> DataFrame:
    """The rows of ``docs`` whose score reaches the threshold, with their score as ``name`` if one is given.

    Rows with a NULL text have nothing to judge and go; an empty text is judged by its
    statistics like any other.  Ids play no part, so NULL and repeated ones are judged row by
    row.  The other columns come back unchanged; a name they have already gets a ``_`` before it.
    Texts are read whole.  An empty table gives an empty table.
    """
    (score,) = fresh(docs, name or "quality_score")
    judged = with_quality(docs, trees, score, text_col).where(F.col(score) >= trees.threshold)
    return judged.select(*[F.col(f"`{c}`") for c in docs.columns], *([F.col(score)] if name else []))
