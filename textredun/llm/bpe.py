"""Byte-level BPE with a hierarchical-bitmap rank queue.

Merging keeps the pre-token as a linked list and its adjacent pairs in buckets, one per
merge rank, each holding list positions.  Which buckets are filled is written in a
three-level bitmap of 64-bit words, so the next rank is found by three find-first-set
steps instead of a heap over all pairs; an entry whose pair has changed meanwhile is
skipped when its turn comes.  Each merge costs a constant number of such steps, which keeps
pre-tokens of any length near linear; short ones are answered by a cache.
"""

from __future__ import annotations

import base64
import itertools
import re
from heapq import heappop, heappush
from pathlib import Path
from struct import pack

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import Memo, kept

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: contractions, letters, digits, other signs (each with an optional blank before), white space
PRE_TOKEN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: the same in the terms of the standard library's matcher, which is faster, for texts without a character that the two see differently
PLAIN_PRE_TOKEN = re.compile(r"'(?:[sdmt]|ll|ve|re)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+").findall
NOT_PLAIN = re.compile("[\x1c-\x1f²³¹¼-¾\u0250-\u200f\u2028-\U0010ffff]").search
LONG_PIECE = 64


BIT = [1 << i for i in range(64)]


class Pieces(Memo):
    """A cache that keeps no long pieces."""

    def __missing__(self, piece: str) -> bytes:
        return self.compute(piece) if len(piece) > LONG_PIECE else super().__missing__(piece)


class RankQueue:
    """Positions by rank; lowest rank first and, within a rank, lowest position first.

    A bucket is a bare position, or a heap of them once there are two.
    """

    def __init__(self, n_ranks: int):
        self.buckets: dict[int, int | list[int]] = {}
        self.words = [0] * ((n_ranks >> 6) + 1)
        self.groups = [0] * ((n_ranks >> 12) + 1)
        self.top = 0

    def push(self, rank: int, position: int) -> None:
        held = self.buckets.get(rank)
        if held is None:
            self.buckets[rank] = position
            self.words[rank >> 6] |= BIT[rank & 63]
            self.groups[rank >> 12] |= BIT[rank >> 6 & 63]
            self.top |= BIT[rank >> 12]
        elif held.__class__ is list:
            heappush(held, position)
        else:
            self.buckets[rank] = [held, position] if held < position else [position, held]

    def pop(self) -> tuple[int, int]:
        """The next entry; only while ``top`` is not 0."""
        top = self.top
        g = (top & -top).bit_length() - 1
        group = self.groups[g]
        w = g << 6 | (group & -group).bit_length() - 1
        word = self.words[w]
        rank = w << 6 | (word & -word).bit_length() - 1
        held = self.buckets[rank]
        if held.__class__ is list:
            position = heappop(held)
            if len(held) == 1:
                self.buckets[rank] = held[0]
            return rank, position
        del self.buckets[rank]
        self.words[w] = word = word & (word - 1)
        if not word:
            self.groups[g] = group = group & (group - 1)
            if not group:
                self.top = top & (top - 1)
        return rank, held


class Bpe:
    """Encoder and decoder over a vocabulary of ``bytes -> rank``; a rank is also the token's id."""

    def __init__(self, ranks: dict[bytes, int], pattern: str = PRE_TOKEN, cache: int = 1_000_000):
        missing = [b for b in range(256) if bytes([b]) not in ranks]
        if missing:
            raise ValueError(f"the vocabulary lacks the bytes {missing[:5]}")
        self.ranks = ranks
        self.size = max(ranks.values()) + 1
        self.bytes_of: list[bytes] = [b""] * self.size
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
        self.single = [ranks[bytes([b])] for b in range(256)]
        self.full_split = regex.compile(pattern).findall
        self.plain = pattern == PRE_TOKEN
        self.queue = RankQueue(self.size)
        self.pair_rank = Memo(lambda pair: ranks.get(self.bytes_of[pair[0]] + self.bytes_of[pair[1]], -1), limit=250_000)
        self.cached = Pieces(self.packed_piece, limit=cache)

    @classmethod
    def load(cls, path: str = VOCABULARY, **options) -> Bpe:
        lines = Path(path).read_bytes().split(b"\n")
        return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, filter(None, lines))}, **options)

    def split(self, text: str) -> list[str]:
        """Pre-tokens of a text."""
        return PLAIN_PRE_TOKEN(text) if self.plain and NOT_PLAIN(text) is None else self.full_split(text)

    def encode_piece(self, piece: str) -> tuple[int, ...]:
        """Token ids of one pre-token."""
        raw = piece.encode()
        whole = self.ranks.get(raw)
        return (whole,) if whole is not None else self.merge(raw)

    def merge(self, raw: bytes) -> tuple[int, ...]:
        """Merges lowest rank first, leftmost first within a rank; the queue's steps are written out here, as calls would cost half the time."""
        pair_rank, bit = self.pair_rank, BIT
        buckets, words, groups, top = self.queue.buckets, self.queue.words, self.queue.groups, 0
        token = [self.single[b] for b in raw]
        n = len(token)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank_at = [pair_rank[pair] for pair in zip(token, token[1:])]  # of the pair that begins here; -1: none
        rank_at.append(-1)
        new = [(r, i) for i, r in enumerate(rank_at) if r >= 0]
        while True:
            for r, i in new:
                held = buckets.get(r)
                if held is None:
                    buckets[r] = i
                    w = r >> 6
                    if not words[w]:
                        groups[w >> 6] |= bit[w & 63]
                        top |= bit[w >> 6]
                    words[w] |= bit[r & 63]
                elif held.__class__ is list:
                    heappush(held, i)
                else:
                    buckets[r] = [held, i] if held < i else [i, held]
            if not top:
                return tuple([t for t in token if t >= 0])
            new = ()
            g = (top & -top).bit_length() - 1
            group = groups[g]
            w = g << 6 | (group & -group).bit_length() - 1
            word = words[w]
            rank = w << 6 | (word & -word).bit_length() - 1
            i = buckets[rank]
            if i.__class__ is list:
                held = i
                i = heappop(held)
                if len(held) == 1:
                    buckets[rank] = held[0]
            else:
                del buckets[rank]
                words[w] = word = word & (word - 1)
                if not word:
                    groups[g] = group = group & (group - 1)
                    if not group:
                        top &= top - 1
            if rank_at[i] != rank:
                continue  # stale: the pair has been merged away or changed
            j = after[i]
            token[i], token[j], rank_at[j] = rank, -1, -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                r = rank_at[i] = pair_rank[rank, token[k]]
                if r >= 0:
                    new = ((r, i),)
            else:
                rank_at[i] = -1
            h = before[i]
            if h >= 0:
                r = rank_at[h] = pair_rank[token[h], rank]
                if r >= 0:
                    new = (*new, (r, h))

    def packed_piece(self, piece: str) -> bytes:
        ids = self.encode_piece(piece)
        return pack(f"={len(ids)}i", *ids)

    def encode_array(self, text: str) -> np.ndarray:
        """Token ids of a text as int32."""
        return np.frombuffer(b"".join(map(self.cached.__getitem__, self.split(text))), dtype=np.int32)

    def encode(self, text: str) -> list[int]:
        return self.encode_array(text).tolist()

    def decode_bytes(self, ids) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def decode(self, ids) -> str:
        """Text of ids; bytes that are no UTF-8, as in ids cut out of a text, become U+FFFD."""
        return self.decode_bytes(ids).decode("utf-8", errors="replace")


def _lists(rows: list[np.ndarray | None]) -> pa.Array:
    ends = np.zeros(len(rows) + 1, dtype=np.int32)
    np.cumsum([0 if r is None else len(r) for r in rows], out=ends[1:])
    flat = np.concatenate([np.empty(0, dtype=np.int32), *(r for r in rows if r is not None)])
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat), mask=pa.array([r is None for r in rows]))


def encode(docs: DataFrame, vocabulary: str = VOCABULARY, id_col: str = "doc_id", text_col: str = "text", check: bool = False) -> DataFrame:
    """``doc_id, n_tokens, tokens`` of every row, and with ``check`` whether decoding gives the text back, byte for byte, as ``exact``.

    NULL texts have NULL tokens (and no count); an empty text has none.  Special tokens'
    strings are ordinary text.  A pre-token of any length is encoded whole.  NULL and repeated
    ids are kept as they come.  An empty table gives an empty table; other columns are ignored.
    ``vocabulary`` is a file of ``base64(token) rank`` lines; the driver reads it and broadcasts its ranks.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    spark = docs.sparkSession
    ranks = spark.sparkContext.broadcast(Bpe.load(vocabulary).ranks)

    def run(batches):
        bpe = kept(("bpe", vocabulary), lambda: Bpe(ranks.value))
        for whole in batches:
            for b in (whole.slice(i, 500) for i in range(0, whole.num_rows, 500)):
                texts = b.column(1).to_pylist()
                ids = [None if t is None else bpe.encode_array(t) for t in texts]
                columns = [b.column(0), pa.array([None if r is None else len(r) for r in ids], type=pa.int32()), _lists(ids)]
                if check:
                    columns.append(pa.array([None if r is None else bpe.decode_bytes(r.tolist()) == t.encode() for r, t in zip(ids, texts)], type=pa.bool_()))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_tokens", "tokens", "exact"][: len(columns)])

    return rows.mapInArrow(run, "doc_id bigint, n_tokens int, tokens array<int>" + ", exact boolean" * check)


def decode(tokens: DataFrame, vocabulary: str = VOCABULARY, id_col: str = "doc_id", token_col: str = "tokens") -> DataFrame:
    """``doc_id, text`` of rows of token ids; NULL for NULL tokens. An id outside the vocabulary is an error."""
    rows = tokens.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{token_col}`").alias("tokens"))
    ranks = tokens.sparkSession.sparkContext.broadcast(Bpe.load(vocabulary).ranks)

    def run(batches):
        bpe = kept(("bpe", vocabulary), lambda: Bpe(ranks.value))
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if r is None else bpe.decode(r) for r in b.column(1).to_pylist()], type=pa.string())], ["doc_id", "text"])

    return rows.mapInArrow(run, "doc_id bigint, text string")
