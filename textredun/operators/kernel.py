"""Exact n-gram counting of many texts at once, for every length up to a maximum.

The units of a batch of texts (code points, words or lines) become small integers.  The key of an
n-gram is the number that its text and units spell, so equal n-grams of one text, and only they, share a
key: no hashing, no collisions.  One sort of the keys counts all texts.  Where a longer key would not fit 62
bits, the key so far gives way to its rank among the keys of its length.
"""

from __future__ import annotations

import re
import sys
import types

import numpy as np

TOKEN = re.compile(r"[^ \t\n\x0b\f\r]+")  # what Java's \s parts, so that all strategies agree


def kept(key, make):
    """A value that a worker process makes once and keeps for its later tasks."""
    held = sys.modules.setdefault("_kept_by_worker", types.ModuleType("_kept_by_worker")).__dict__
    if key not in held:
        held[key] = make()
    return held[key]


def slices(texts: list[str], rows: int = 100, chars: int = 500_000):
    """``texts`` in runs of at most ``rows`` texts and about ``chars`` characters; a longer text is a run of its own."""
    begin, size = 0, 0
    for i, t in enumerate(texts):
        if i > begin and (i - begin >= rows or size + len(t) > chars):
            yield begin, texts[begin:i]
            begin, size = i, 0
        size += len(t)
    if begin < len(texts):
        yield begin, texts[begin:]


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(code points of all texts, ends of texts)."""
    raw = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.int64)
    return raw, ends_of(texts)


def ends_of(rows: list) -> np.ndarray:
    ends = np.zeros(len(rows) + 1, dtype=np.int64)
    np.cumsum([len(r) for r in rows], out=ends[1:])
    return ends


def numbered(rows: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
    """(number of each unit, ends of texts) where equal strings have equal numbers."""
    known: dict[str, int] = {}
    flat = np.fromiter((known.setdefault(u, len(known)) for r in rows for u in r), dtype=np.int64)
    return flat, ends_of(rows)


def units_of(texts: list[str], unit: str) -> tuple[np.ndarray, np.ndarray]:
    """Units of texts: ``char``: code points; ``token``: what white space parts; ``line``: what line ends part."""
    if unit == "char":
        return code_points(texts)
    if unit == "token":
        return numbered([TOKEN.findall(t) for t in texts])
    if unit == "line":
        return numbered([t.split("\n") for t in texts])
    raise ValueError(f"unknown unit {unit!r}")


def _dense(codes: np.ndarray) -> tuple[np.ndarray, int]:
    """Small non-negative integers as their ranks among those that occur, and how many do."""
    if not len(codes):
        return codes, 0
    there = np.zeros(int(codes.max()) + 1, dtype=np.int64)
    there[codes] = 1
    rank = np.cumsum(there)
    return (rank - 1)[codes], int(rank[-1])


def profiles(codes: np.ndarray, ends: np.ndarray, lengths: list[int]):
    """For each of ``lengths``: (length, text of each distinct n-gram, its count).  Texts come in order."""
    unit, n_units = _dense(codes)
    n_units = max(n_units, 1)
    left = np.repeat(ends[1:], np.diff(ends)) - np.arange(len(codes))  # units from here to the end of the text
    key = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
    owner_of, size, span = np.arange(len(ends) - 1), max(len(ends) - 1, 1), 1  # a key over ``span`` numbers its n-gram's beginning
    for n in range(1, max(lengths, default=0) + 1):
        if size * n_units >= 1 << 62:
            distinct, key = np.unique(key, return_inverse=True)
            owner_of, size, span = owner_of[distinct // span], max(len(distinct), 1), 1
        # keys that run into the next text are dropped when they are counted
        key = key[: max(len(codes) - n + 1, 0)] * n_units + unit[n - 1 :]
        size, span = size * n_units, span * n_units
        if n in lengths:
            ordered = np.sort(key[left[: len(key)] >= n])
            first = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(ordered) else np.zeros(0, dtype=np.int64)
            yield n, owner_of[ordered[first] // span], np.diff(np.append(first, len(ordered)))


def spectra_of(codes: np.ndarray, ends: np.ndarray, lengths: list[int]):
    """For each of ``lengths``: (length, N, V, ends, c, v): N n-grams and V distinct ones of each text; its spectrum, c falling, is ``ends[i]:ends[i+1]`` of (c, v)."""
    n_texts = len(ends) - 1
    for n, text_of, counts in profiles(codes, ends, lengths):
        total = np.bincount(text_of, weights=counts, minlength=n_texts).astype(np.int64)
        types = np.bincount(text_of, minlength=n_texts)
        widest = int(counts.max(initial=0)) + 1
        key, times = np.unique(text_of * widest + (widest - 1 - counts), return_counts=True)
        text, c = key // widest, widest - 1 - key % widest
        cut = np.zeros(n_texts + 1, dtype=np.int64)
        np.cumsum(np.bincount(text, minlength=n_texts), out=cut[1:])
        yield n, total, types, cut, c, times
