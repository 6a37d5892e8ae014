"""Fuzzy search for short license notices.

A notice that occurs with at most k edits contains at least one of k + 1 pieces of itself
unchanged.  One Aho-Corasick automaton finds the pieces of all notices in a text; each hit
opens a window.  A bit-parallel pass over the window tells where an occurrence may end and
with how few edits, and the bounded-error matcher of the ``regex`` library, allowed
just so many, verifies it and reports the span.  (The matcher alone tries a number of ways
exponential in the edits on windows without any occurrence.)  One narrow pass, no shuffle.
"""

from __future__ import annotations

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import kept

SCHEMA = "doc_id bigint, notice string, span_start int, span_end int, edits int, matched string"
#: notice -> how it reads, in lower case with single blanks
NOTICES = {
    "Apache-2.0": "licensed under the apache license, version 2.0",
    "MIT": "released under the mit license",
    "MIT-grant": "permission is hereby granted, free of charge, to any person obtaining a copy",
    "GPL": "licensed under the gnu general public license, version 3",
    "GPL-redistribute": "under the terms of the gnu general public license as published by the free software foundation",
    "LGPL": "gnu lesser general public license",
    "MPL-2.0": "subject to the terms of the mozilla public license",
    "BSD": "redistribution and use in source and binary forms, with or without modification",
    "CC-BY-NC": "licensed under cc by-nc 4.0",
    "CC-BY": "licensed under a creative commons attribution",
    "SPDX": "spdx-license-identifier:",
    "reserved": "all rights reserved",
    "copyright": "copyright (c) ",
}
ERROR_SHARE = 0.1


def errors_allowed(notice: str, share: float = ERROR_SHARE) -> int:
    return int(len(notice) * share)


def pieces(notice: str, k: int) -> list[tuple[int, str]]:
    """(offset, piece) of the k + 1 pieces, of lengths that differ by 1 at most."""
    cuts = [len(notice) * i // (k + 1) for i in range(k + 2)]
    return [(a, notice[a:b]) for a, b in zip(cuts, cuts[1:])]


def folded(text: str) -> str:
    """Lower case and white space as blanks, character for character, so spans stay those of the text."""
    low = text.lower()
    if len(low) != len(text):
        low = "".join([c if len(c := o.lower()) == 1 else o for o in text])
    for space in "\t\n\r\f\v":
        low = low.replace(space, " ")
    return low


def ends_within(masks: dict[str, int], n: int, k: int, text: str) -> list[tuple[int, int]]:
    """(end, edits) of each place in ``text`` where a stretch within ``k`` edits of the notice ends: the column of edit distances, as two bit rows of its steps."""
    full, top = (1 << n) - 1, 1 << (n - 1)
    up, down, edits = full, 0, n
    out = []
    for end, c in enumerate(text, 1):
        eq = masks.get(c, 0)
        d = ((((eq & up) + up) ^ up) | eq | down) & full
        rise, fall = (down | ~(d | up)) & full, up & d
        if rise & top:
            edits += 1
        elif fall & top:
            edits -= 1
        rise, fall = rise << 1 & full, fall << 1 & full  # a match may begin anywhere: row 0 stays 0
        up, down = (fall | ~(d | rise)) & full, rise & d
        if edits <= k:
            out.append((end, edits))
    return out


class Scanner:
    """Finds every notice within its allowed edits."""

    def __init__(self, notices: dict[str, str] = NOTICES, share: float = ERROR_SHARE):
        self.notices = []
        seeds: dict[str, list[tuple[int, int]]] = {}
        for i, (name, notice) in enumerate(notices.items()):
            k = errors_allowed(notice, share)
            if k >= len(notice):
                raise ValueError(f"{name}: more edits than characters")
            masks: dict[str, int] = {}
            for at, c in enumerate(notice):
                masks[c] = masks.get(c, 0) | 1 << at
            allowed = [regex.compile(f"(?:{regex.escape(notice)}){{e<={e}}}") for e in range(k + 1)]
            self.notices.append((name, len(notice), k, masks, allowed))
            for offset, piece in pieces(notice, k):
                seeds.setdefault(piece, []).append((i, offset))
        self.automaton = ahocorasick.Automaton()
        for piece, owners in seeds.items():
            self.automaton.add_word(piece, (len(piece), owners))
        self.automaton.make_automaton()

    def windows(self, low: str) -> dict[int, list[tuple[int, int]]]:
        """By notice, the stretches that may hold it: all places a seed's hit allows, merged where they overlap."""
        found: dict[int, list[tuple[int, int]]] = {}
        for end, (length, owners) in self.automaton.iter(low):
            start = end - length + 1
            for i, offset in owners:
                n, k = self.notices[i][1:3]
                a, b = max(0, start - offset - k), min(len(low), start - offset + n + k)
                found.setdefault(i, []).append((a, b))
        for stretches in found.values():
            stretches.sort()
            merged = stretches[:1]
            for a, b in stretches[1:]:
                if a <= merged[-1][1]:
                    merged[-1] = (merged[-1][0], max(b, merged[-1][1]))
                else:
                    merged.append((a, b))
            stretches[:] = merged
        return found

    def scan(self, text: str) -> list[tuple[str, int, int, int]]:
        """(notice, start, end, edits) of each occurrence, by place.

        Ends that follow on one another belong to one occurrence, which is reported with
        the fewest edits that any of them needs, at the first place that needs no more.
        """
        low, out = folded(text), []
        for i, stretches in self.windows(low).items():
            name, n, k, masks, allowed = self.notices[i]
            for a, b in stretches:
                groups: list[list[tuple[int, int]]] = []
                for end, edits in ends_within(masks, n, k, low[a:b]):
                    if groups and end == groups[-1][-1][0] + 1:
                        groups[-1].append((end, edits))
                    else:
                        groups.append([(end, edits)])
                for group in groups:
                    fewest = min(e for _, e in group)
                    end = next(end for end, e in group if e == fewest)
                    m = allowed[fewest].search(low, max(a, a + end - n - fewest), a + end)
                    if m:
                        out.append((name, m.start(), m.end(), sum(m.fuzzy_counts)))
        return sorted(out, key=lambda r: (r[1], r[2], r[0]))


def scan_licenses(docs: DataFrame, notices: dict[str, str] | None = None, share: float = ERROR_SHARE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per place where a notice occurs within ``share`` of its length in edits.

    ``span_start, span_end`` count code points from 0; case and kinds of white space are no
    edits.  NULL and empty texts and empty tables give no rows; texts of any length are read whole; rows with NULL or
    repeated ids are scanned like any other.  Other columns are ignored.
    """
    notices = dict(NOTICES if notices is None else notices)
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).where("text IS NOT NULL")
    types = [pa.int64(), pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.string()]

    def run(batches):
        scanner = kept(("license scanner", tuple(notices.items()), share), lambda: Scanner(notices, share))
        for b in batches:
            out = [(key, name, s, e, edits, text[s:e]) for key, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for name, s, e, edits in scanner.scan(text)]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(zip(*out), types)], ["doc_id", "notice", "span_start", "span_end", "edits", "matched"])

    return rows.mapInArrow(run, SCHEMA)
