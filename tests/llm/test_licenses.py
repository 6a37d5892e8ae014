import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from textredun.llm import licenses as L

DOCS = "doc_id bigint, text string"


def by_table(text):
    """(notice, last end of a run of ends, fewest edits) from the full table of edit distances, row by row."""
    low, out = L.folded(text), []
    for name, notice in L.NOTICES.items():
        k = L.errors_allowed(notice)
        row = np.zeros(len(low) + 1, dtype=np.int64)  # an occurrence may begin anywhere
        at = np.arange(len(low) + 1)
        codes = np.array([ord(c) for c in low])
        for i, c in enumerate(notice, 1):
            new = np.concatenate([[i], np.minimum(row[1:] + 1, row[:-1] + (codes != ord(c)))]) if len(low) else np.array([i])
            row = np.minimum.accumulate(new - at) + at
        ends = np.flatnonzero(row <= k)
        for run in np.split(ends, np.flatnonzero(np.diff(ends) > 1) + 1):
            if len(run):
                out.append((name, int(run[row[run].argmin()]), int(row[run].min())))
    return sorted(out)


def occurrences(found):
    return sorted((name, e, k) for name, _, e, k in found)


def edited(rng, s, k):
    for _ in range(k):
        i = rng.randrange(1, len(s) - 1)
        s = rng.choice([s[:i] + s[i + 1 :], s[:i] + rng.choice("qxz") + s[i:], s[:i] + rng.choice("qxz") + s[i + 1 :]])
    return s


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, old = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(old[j] + 1, row[-1] + 1, old[j - 1] + (x != y)))
    return row[-1]


@pytest.mark.parametrize("seed", range(15))
def test_seeds_lose_nothing(seed):
    rng, scanner = random.Random(seed), L.Scanner()
    parts = []
    for name, notice in L.NOTICES.items():
        parts += [" ".join(rng.choices(["lorem", "license", "under", "rights", "1.0"], k=6)), edited(rng, notice.upper() if rng.random() < 0.3 else notice, rng.randint(0, L.errors_allowed(notice)))]
    rng.shuffle(parts)
    text = "\n".join(parts)
    found = scanner.scan(text)
    assert occurrences(found) == by_table(text)
    assert {r[0] for r in found} == set(L.NOTICES)
    for name, s, e, k in found:
        assert distance(L.folded(text)[s:e], L.NOTICES[name]) <= k <= L.errors_allowed(L.NOTICES[name])


def test_documents_equal_the_full_table(spark, data):
    docs = spark.read.parquet(data("0.01") + "/documents.parquet")
    want = sorted((r.doc_id, *x) for r in docs.collect() for x in by_table(r.text))
    got = sorted((r.doc_id, r.notice, r.span_end, r.edits) for r in L.scan_licenses(docs).collect())
    assert got == want and len(got) > 20


def test_edges_of_input(spark):
    note = "All\tRights\nReserved"
    rows = [(1, None), (2, ""), (3, "İİ " + note), (None, note), (4, note), (4, note), (5, "x" * 500_000 + "al rights reserved" + "y" * 500_000), (6, "all wrongs reserved")]
    df = spark.createDataFrame(rows, DOCS).withColumn("notice", F.lit(1)).withColumn("matched", F.lit(2))
    got = L.scan_licenses(df).collect()
    assert sorted((r.doc_id or 0, r.edits) for r in got) == [(0, 0), (3, 0), (4, 0), (4, 0), (5, 1)]
    assert [r.matched for r in got if r.doc_id == 3] == [note] and [r.span_start for r in got if r.doc_id == 3] == [3]
    assert L.scan_licenses(df.limit(0)).count() == 0
