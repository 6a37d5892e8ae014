"""Near-duplicate search on SimHash fingerprints with vantage-point trees.

Every text gets a 64-bit SimHash of its set of words, which is searched, and one
of its word pairs, which confirms.  Two fingerprints within ``radius`` bits must
agree within ``radius // 4`` bits on at least one of their four 16-bit blocks, so
each block gets its own vantage-point tree.  A 64-bit ball would overlap nearly
every branch; a 16-bit one is small enough for the triangle bound to prune.

The upper levels of a tree are built on the driver from the counts of block values
(65,536 at most for each tree, whatever the input) and split fingerprints into
shards of equal weight, the more of them the more fingerprints there are; a task
searches one shard after the other.  Every fingerprint lives in one shard of each tree and
visits each later shard that its ball may overlap.  Inside a shard the tree goes
on while it prunes; where homes' own block values select fewer, each meets only the values within
reach of its own (``by_value``), and leaves compare whole fingerprints.  The result is exact: all pairs within
the radius, each once.

Copies with one fingerprint are folded before the search, so a group of thousands
costs as much as one document there.  ``near_classes`` gives a row per document, with its class and its number of links;
``near_pairs`` gives links with the smallest id of a group.  ``all_pairs`` unfolds the groups: its rows grow with
the square of a group.
"""

from __future__ import annotations

import hashlib
import itertools
import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textredun.llm.common import Memo, cut_lineage, fresh, kept, mix64, offsets, tasks_for

RADIUS = 10
CONFIRM = 20
LEVELS = (6, 12)  # upper levels of a tree, at least and at most
SHARD_ROWS = 20_000  # fingerprints that live in a shard, about
BLOCKS, BLOCK_BITS = 4, 16
WORD = re.compile(r"\w+")
FINGERPRINT_SCHEMA = "doc_id bigint, fp bigint, confirm bigint"


def _lanes() -> np.ndarray:
    """For each byte value, its eight bits spread over the bytes of a uint64."""
    bits = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little")
    return np.ascontiguousarray(bits).view(np.uint64).ravel()


def word_hash(word: str) -> int:
    """The first eight bytes of a word's MD5 digest."""
    return int.from_bytes(hashlib.md5(word.encode("utf-8", "surrogatepass"), usedforsecurity=False).digest()[:8], "big")


def majority(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """SimHash of each run ``hashes[starts[i]:starts[i + 1]]``: bit b is set where over half of the hashes have it.

    Eight one-byte counters share a word, so a run is added up in slices of at most 255 hashes.
    """
    lengths = np.diff(starts)
    owner = np.repeat(np.arange(len(lengths)), -(-lengths // 255))
    if not len(owner):
        return np.zeros(len(lengths), dtype=np.uint64)
    first = np.concatenate([[True], owner[1:] != owner[:-1]])
    rank = np.arange(len(owner)) - np.maximum.accumulate(np.where(first, np.arange(len(owner)), 0))
    cuts = starts[owner] + rank * 255
    counts = np.zeros((len(lengths), 64), dtype=np.int64)
    lut, octets = _lanes(), hashes.view(np.uint8).reshape(-1, 8)
    for byte in range(8):
        part = np.add.reduceat(lut[octets[:, byte]], cuts).view(np.uint8).reshape(-1, 8)
        np.add.at(counts[:, byte * 8 : byte * 8 + 8], owner, part)
    bits = (counts * 2 > lengths[:, None]).astype(np.uint8)
    return np.packbits(bits, axis=1, bitorder="little").view(np.uint64).ravel()


def _fingerprints(texts: list[str | None], code: Memo) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word fingerprint, pair fingerprint, whether the text has a word)."""
    words = [WORD.findall(t.lower()) if t else [] for t in texts]
    sets = [set(w) for w in words]
    starts = offsets(map(len, sets))
    flat = np.fromiter(map(code.__getitem__, itertools.chain.from_iterable(sets)), dtype=np.uint64, count=starts[-1])
    order = np.fromiter(map(code.__getitem__, itertools.chain.from_iterable(words)), dtype=np.uint64)
    ends = offsets(map(len, words))
    # Pairs of neighbouring words; the pair that would run into the next text is cut off, a lone word stands for itself.
    keep = np.ones(len(order), dtype=bool)
    lengths = np.diff(ends)
    keep[ends[1:][lengths > 1] - 1] = False
    after = np.append(order[1:], order[:1]) if len(order) else order
    alone = np.zeros(len(order), dtype=bool)
    alone[ends[:-1][lengths == 1]] = True
    pairs = mix64(np.where(alone, order, order * np.uint64(0x9E3779B97F4A7C15) + after))[keep]
    pair_starts = np.concatenate([[0], np.cumsum(np.where(lengths > 1, lengths - 1, lengths))])
    return majority(flat, starts), majority(pairs, pair_starts), lengths > 0


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", whole: bool = False) -> DataFrame:
    """``doc_id, fp, confirm`` of each document that has an id and at least one word; with ``whole`` of every row, NULL fingerprints for those without."""
    rows = docs.select(F.col(f"`{id_col}`").cast("bigint").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    rows = rows if whole else rows.where("doc_id IS NOT NULL AND text IS NOT NULL")

    def run(batches):
        code = kept("word hashes", lambda: Memo(word_hash))
        for batch in batches:
            for b in (batch.slice(i, 300) for i in range(0, batch.num_rows, 300)):
                fp, confirm, some = _fingerprints(b.column(1).to_pylist(), code)
                if whole:
                    yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x.view(np.int64), mask=~some) for x in (fp, confirm))], ["doc_id", "fp", "confirm"])
                    continue
                yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(some)), pa.array(fp[some].view(np.int64)), pa.array(confirm[some].view(np.int64))], ["doc_id", "fp", "confirm"])

    return rows.mapInArrow(run, FINGERPRINT_SCHEMA)


# --- vantage-point trees over 16-bit blocks -------------------------------------------------------------


def split(distance: np.ndarray, weight: np.ndarray) -> int | None:
    """The ``mu`` whose halves ``distance <= mu`` and ``distance > mu`` weigh most nearly the same; None if all are as far."""
    total = np.bincount(distance, weights=weight)
    below = np.cumsum(total)[:-1]
    both = (below > 0) & (below < total.sum())
    return int(np.where(both, np.abs(below * 2 - total.sum()), np.inf).argmin()) if both.any() else None


def best_vantage(values: np.ndarray, weight: np.ndarray, tries: int = 8) -> tuple[int, int] | None:
    """(vantage point, mu) of the candidate whose split leaves the least weight near the boundary."""
    best = None
    for v in values[np.linspace(0, len(values) - 1, min(tries, len(values))).astype(int)]:
        d = np.bitwise_count(values ^ v)
        mu = split(d, weight)
        if mu is not None:
            near = weight[(d == mu) | (d == mu + 1)].sum() + abs(weight[d <= mu].sum() * 2 - weight.sum()) / 2
            if best is None or near < best[0]:
                best = (near, int(v), mu)
    return best and best[1:]


def routes(weight: np.ndarray, radius: int, levels: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """A tree's upper levels applied to all block values: the home shard of each value, and for each shard the values that visit it.

    A value visits the shards after its home that may hold a value within ``radius``.
    """
    values = np.arange(1 << BLOCK_BITS, dtype=np.uint16)
    home = np.zeros(len(values), dtype=np.int32)
    visits: list[np.ndarray] = []

    def descend(inside, reach, depth):
        seen = inside[weight[inside] > 0]
        vantage = best_vantage(values[seen], weight[seen]) if depth and len(seen) > 1 else None
        if vantage is None:
            shard = len(visits)
            home[inside] = shard
            visits.append(reach)
            return
        v, mu = np.uint16(vantage[0]), vantage[1]
        d, e = np.bitwise_count(values[inside] ^ v).astype(int), np.bitwise_count(values[reach] ^ v).astype(int)
        descend(inside[d <= mu], reach[e - radius <= mu], depth - 1)
        descend(inside[d > mu], reach[e + radius > mu], depth - 1)

    everything = np.arange(len(values))
    descend(everything, everything, levels)
    return home, [reach[home[reach] < shard] for shard, reach in enumerate(visits)]


def search(home: np.ndarray, guest: np.ndarray, block: int, block_radius: int, radius: int, leaf: int = 1 << 18):
    """Yields (i, j) index arrays of pairs within ``radius``: home with a later home, or home with guest (j counted after the homes).

    A pair whose blocks also agree in an earlier tree is left to that tree.  Where the tree does not go on, homes meet either all
    that came with them or, if that is less work, only those whose block values lie within ``block_radius`` of their own.
    """
    both = np.concatenate([home, guest])
    part = ((both >> np.uint64(block * BLOCK_BITS)) & np.uint64(0xFFFF)).astype(np.uint16)
    masks = masks_within(block_radius)
    todo = [(np.arange(len(home)), np.arange(len(both)))]
    while todo:
        h, q = todo.pop()
        if not len(h) or not len(q):
            continue
        if len(h) * len(q) > leaf:
            values, counts = np.unique(part[h], return_counts=True)
            if len(values) * (len(masks) * VALUE_COST[0] + VALUE_COST[1]) < len(h) * len(q):
                there = np.bincount(part[q], minlength=1 << BLOCK_BITS)
                meet = sum((counts[at : at + 256] * there[values[at : at + 256, None] ^ masks].sum(axis=1)).sum() for at in range(0, len(values), 256))
                if meet + len(values) * (len(masks) * VALUE_COST[0] + VALUE_COST[1]) < 0.5 * len(h) * len(q):
                    for i, j in by_value(both, part, h, q, masks, radius):
                        yield from _own(both, i, j, block, block_radius)
                    continue
            vantage = best_vantage(values, counts.astype(float))
            if vantage is not None:
                v, mu = np.uint16(vantage[0]), vantage[1]
                d, e = np.bitwise_count(part[h] ^ v).astype(int), np.bitwise_count(part[q] ^ v).astype(int)
                sides = [(h[d <= mu], q[e - block_radius <= mu]), (h[d > mu], q[e + block_radius > mu])]
                if sum(len(a) * len(b) for a, b in sides) < 0.95 * len(h) * len(q):
                    todo += sides
                    continue
        rows = max(1, (1 << 20) // len(q))
        for at in range(0, len(h), rows):
            some = h[at : at + rows]
            a, b = np.nonzero(np.bitwise_count(both[some][:, None] ^ both[q][None, :]) <= radius)
            yield from _own(both, some[a], q[b], block, block_radius)


#: what a block value costs in ``by_value``, in comparisons: for each mask, and besides
VALUE_COST = (40, 20_000)


def masks_within(radius: int) -> np.ndarray:
    """The block values of at most ``radius`` bits."""
    values = np.arange(1 << BLOCK_BITS, dtype=np.uint16)
    return values[np.bitwise_count(values) <= radius]


def by_value(both: np.ndarray, part: np.ndarray, h: np.ndarray, q: np.ndarray, masks: np.ndarray, radius: int, cells: int = 1 << 20):
    """Yields (i, j) of ``h`` and ``q`` within ``radius`` whose block values differ by one of ``masks``."""
    h, q = h[np.argsort(part[h], kind="stable")], q[np.argsort(part[q], kind="stable")]
    starts = np.searchsorted(part[q], np.arange((1 << BLOCK_BITS) + 1))
    prints = both[q]
    edges = np.flatnonzero(np.concatenate([[True], part[h][1:] != part[h][:-1], [True]]))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist()):
        near = (part[h[a]] ^ masks).astype(np.int64)
        begin, n = starts[near], starts[near + 1] - starts[near]
        begin, n = begin[n > 0], n[n > 0]
        some = np.repeat(begin - (np.cumsum(n) - n), n) + np.arange(n.sum())
        if not len(some):
            continue
        theirs, rows = prints[some], max(1, cells // len(some))
        for at in range(a, b, rows):
            mine = h[at : min(b, at + rows)]
            hit = np.flatnonzero(np.bitwise_count(both[mine][:, None] ^ theirs[None, :]) <= radius)
            if len(hit):
                yield mine[hit // len(some)], q[some[hit % len(some)]]


def _own(both: np.ndarray, i: np.ndarray, j: np.ndarray, block: int, block_radius: int):
    """Of close pairs those with i before j that this block's tree finds first."""
    x = both[i] ^ both[j]
    ok = j > i
    for earlier in range(block + 1):
        near = np.bitwise_count((x >> np.uint64(earlier * BLOCK_BITS)) & np.uint64(0xFFFF)) <= block_radius
        ok &= near if earlier == block else ~near
    if ok.any():
        yield i[ok], j[ok]


def least_reachable(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """For each of n nodes, the smallest node that a path along the edges (i, j) leads to."""
    low = np.arange(n)
    while True:
        before = low.copy()
        least = np.minimum(low[i], low[j])
        np.minimum.at(low, i, least)
        np.minimum.at(low, j, least)
        low = low[low]
        if (low == before).all():
            return low


def near_fingerprints(folded: DataFrame, radius: int = RADIUS, confirm: int = CONFIRM, levels: int | None = None, forest: bool = False, degrees: bool = False) -> DataFrame:
    """All pairs of distinct (``doc_id, fp, confirm``) rows within ``radius`` bits in ``fp`` and ``confirm`` bits in ``confirm``.

    Gives ``doc_a < doc_b, distance``.  ``folded`` is read twice: pass something materialised.
    With ``forest``, each shard gives only one link (distance NULL) for each document that
    its pairs connect to one with a smaller id: paths lead to the same documents, but the rows grow with the
    documents, not with their pairs.  With ``degrees`` too, ``folded`` says in ``n`` how many documents a row stands for, and rows
    ``doc_a`` with ``doc_b`` NULL give in ``distance`` how many documents the shard's pairs link to one of ``doc_a``.  ``levels`` of a tree make up to ``2**levels`` shards; by default
    as many as leave about ``SHARD_ROWS`` fingerprints to each.
    """
    if degrees and not forest:
        raise ValueError("degrees go with a forest")
    if not 0 <= radius < 64:
        raise ValueError("radius must be from 0 to 63")
    block_radius = radius // BLOCKS
    blocks = [F.shiftrightunsigned("fp", BLOCK_BITS * t).bitwiseAND(0xFFFF).cast("int") for t in range(BLOCKS)]
    tally = folded.select(F.posexplode(F.array(*blocks)).alias("tree", "value")).groupBy("tree", "value").count().collect()
    weight = np.zeros((BLOCKS, 1 << BLOCK_BITS))
    for tree, value, n in tally:
        weight[tree, value] = n
    if levels is None:
        levels = min(LEVELS[1], max(LEVELS[0], math.ceil(math.log2(max(1, weight[0].sum() / SHARD_ROWS)))))
    targets, home_of, per_tree = [], [], []
    for tree in range(BLOCKS):
        home, visits = routes(weight[tree], block_radius, levels)
        shard = np.concatenate([np.full(len(v), s, dtype=np.int32) for s, v in enumerate(visits)])
        value = np.concatenate(visits)
        order = np.argsort(value, kind="stable")
        targets.append((shard[order], np.searchsorted(value[order], np.arange((1 << BLOCK_BITS) + 1))))
        home_of.append(home)
        per_tree.append(len(visits))
    base = np.concatenate([[0], np.cumsum(per_tree)])
    tables = folded.sparkSession.sparkContext.broadcast((targets, home_of))
    columns = ["doc_id", "fp", "confirm", *(["n"] if degrees else [])]
    packed = np.dtype([("id", "<i8"), ("fp", "<u8"), ("confirm", "<u8"), *([("n", "<i8")] if degrees else [])])
    kinds = pa.schema([("doc_a", pa.int64()), ("doc_b", pa.int64()), ("distance", pa.int64() if degrees else pa.int32())])

    def route(batches):
        """Fingerprints of a task, gathered by shard into one block of bytes each: homes, then guests."""
        targets, home_of = tables.value
        held: dict[tuple[int, bool], list[np.ndarray]] = {}

        def drain():
            keys, blobs = list(held), [np.concatenate(v).tobytes() for v in held.values()]
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys]), pa.array(blobs, pa.binary())], ["shard", "guest", "rows"])

        size = 0
        for b in batches:
            rows = np.empty(b.num_rows, dtype=packed)
            rows["id"] = b.column(0).to_numpy()
            rows["fp"] = b.column(1).to_numpy().view(np.uint64)
            rows["confirm"] = b.column(2).to_numpy().view(np.uint64)
            if degrees:
                rows["n"] = b.column(3).to_numpy()
            for tree in range(BLOCKS):
                value = ((rows["fp"] >> np.uint64(tree * BLOCK_BITS)) & np.uint64(0xFFFF)).astype(np.int64)
                shard, starts = targets[tree]
                n = starts[value + 1] - starts[value]
                copies = np.repeat(np.arange(len(rows)), n)
                within = np.arange(len(copies)) - np.repeat(np.cumsum(n) - n, n)
                for guest, which, to in ((False, np.arange(len(rows)), home_of[tree][value]), (True, copies, shard[starts[value][copies] + within])):
                    order = np.argsort(to, kind="stable")
                    ends = np.flatnonzero(np.diff(to[order])) + 1
                    for run in np.split(order, ends) if len(order) else []:
                        held.setdefault((int(base[tree] + to[run[0]]), guest), []).append(rows[which[run]])
                        size += len(run) * packed.itemsize
            if size > 1 << 26:
                yield drain()
                size = 0
        if held:
            yield drain()

    none = np.empty(0, dtype=packed)

    def one_by_one(batches):
        """(shard, its home rows, its guests) of batches sorted by shard."""
        at, held = None, ([], [])
        for b in batches:
            for s, guest, rows in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if s != at and at is not None:
                    yield at, *(np.concatenate(x) if x else none for x in held)
                    held = ([], [])
                at = s
                held[guest].append(np.frombuffer(rows.as_buffer(), dtype=packed))
        if at is not None:
            yield at, *(np.concatenate(x) if x else none for x in held)

    def pairs(batches):
        for s, home, guest in one_by_one(batches):
            tree = int(np.searchsorted(base, s, side="right")) - 1
            both = np.concatenate([home, guest])
            low, links = np.arange(len(both)), np.zeros(len(both), dtype=np.int64)
            for i, j in search(home["fp"], guest["fp"], tree, block_radius, radius):
                ok = np.bitwise_count(both["confirm"][i] ^ both["confirm"][j]) <= confirm
                if degrees:
                    np.add.at(links, i[ok], both["n"][j[ok]])
                    np.add.at(links, j[ok], both["n"][i[ok]])
                if forest:
                    apart = low[i] != low[j]
                    if (ok & apart).any():
                        fold_in = least_reachable(len(both), low[i[ok & apart]], low[j[ok & apart]])
                        low = fold_in[low]
                    continue
                i, j = both[i[ok]], both[j[ok]]
                if len(i):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.minimum(i["id"], j["id"])), pa.array(np.maximum(i["id"], j["id"])), pa.array(np.bitwise_count(i["fp"] ^ j["fp"]).astype(np.int32))],
                        schema=kinds,
                    )

            if forest and (low != np.arange(len(both))).any():
                least = both["id"].copy()
                np.minimum.at(least, low, both["id"])
                ids, least = both["id"], least[low]
                linked = ids > least
                yield pa.RecordBatch.from_arrays([pa.array(least[linked]), pa.array(ids[linked]), pa.nulls(int(linked.sum()), kinds.field(2).type)], schema=kinds)
            if (links > 0).any():
                yield pa.RecordBatch.from_arrays([pa.array(both["id"][links > 0]), pa.nulls(int((links > 0).sum()), pa.int64()), pa.array(links[links > 0])], schema=kinds)

    shards = folded.select(*columns).mapInArrow(route, "shard int, guest boolean, rows binary")
    return shards.repartition(tasks_for(folded.sparkSession, int(base[-1])), "shard").sortWithinPartitions("shard").mapInArrow(pairs, f"doc_a bigint, doc_b bigint, distance {'bigint' if degrees else 'int'}")


def fold(prints: DataFrame) -> DataFrame:
    """One row per distinct (fp, confirm) with the smallest id that has it."""
    return prints.groupBy("fp", "confirm").agg(F.min("doc_id").alias("doc_id")).select("doc_id", "fp", "confirm")


def near_pairs(docs: DataFrame, radius: int = RADIUS, confirm: int = CONFIRM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Links ``doc_a < doc_b, distance`` of near-duplicate documents, each once; for the pairs see ``all_pairs``.

    Documents with the same fingerprints are listed as links of the smallest id among
    them with each other one (distance 0); documents with different fingerprints are
    compared by those smallest ids, all pairs within ``radius``.  Pairs of other members
    of two groups are not listed.

    Texts that are NULL, empty or without any word, and NULL ids, are in no pair.
    Rows that repeat an id count once.  A text of any length is read whole.  An empty
    table gives no pairs.  Other columns are ignored.
    """
    prints = cut_lineage(fingerprints(docs, id_col, text_col))
    folded = cut_lineage(fold(prints))
    copies = (
        prints.join(folded.withColumnRenamed("doc_id", "doc_a"), ["fp", "confirm"])
        .where("doc_a < doc_id")
        .select("doc_a", F.col("doc_id").alias("doc_b"), F.lit(0).alias("distance"))
        .distinct()
    )
    return copies.unionByName(near_fingerprints(folded, radius, confirm))


def all_pairs(docs: DataFrame, radius: int = RADIUS, confirm: int = CONFIRM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every near-duplicate pair ``doc_a < doc_b, distance`` of documents, each once.

    Groups of equal fingerprints are compared once and unfolded: all pairs within a group,
    and each member of a group with each of every near group.  An id with several texts is in the group of each, and
    of the distances of a pair the smallest counts; otherwise as ``near_pairs``.
    """
    prints = fingerprints(docs, id_col, text_col)
    groups = cut_lineage(prints.groupBy("fp", "confirm").agg(F.sort_array(F.collect_set("doc_id")).alias("ids")).withColumn("group", F.monotonically_increasing_id()))
    near = near_fingerprints(groups.select(F.col("group").alias("doc_id"), "fp", "confirm"), radius, confirm)
    one, two = (groups.select(F.col("group").alias(f"doc_{x}"), F.col("ids").alias(f"ids_{x}")) for x in "ab")
    across = near.join(one, "doc_a").join(two, "doc_b").select("ids_a", "ids_b", "distance")
    across = across.select(F.explode("ids_a").alias("x"), "ids_b", "distance").select("x", F.explode("ids_b").alias("y"), "distance").where("x <> y")
    within = groups.where("size(ids) > 1").select(F.posexplode("ids").alias("at", "x"), "ids")
    within = within.select("x", F.explode(F.expr("slice(ids, at + 2, size(ids))")).alias("y"), F.lit(0).alias("distance"))
    pairs = across.unionByName(within).select(F.least("x", "y").alias("doc_a"), F.greatest("x", "y").alias("doc_b"), "distance")
    repeated = groups.select(F.explode("ids").alias("doc_id")).groupBy("doc_id").count().where("count > 1")
    return pairs if repeated.isEmpty() else pairs.groupBy("doc_a", "doc_b").agg(F.min("distance").alias("distance"))


def components(edges: DataFrame) -> DataFrame:
    """``doc_id, group_id`` for the nodes of ``doc_a, doc_b`` edges: the group is the smallest id that a path leads to.

    Alternates hooking every node's larger neighbours to its smallest one with pulling
    each node to that one, until nothing changes; the rounds grow with the logarithm of
    the longest path.  Lineage is cut each round.
    """
    links = cut_lineage(edges.select(F.least("doc_a", "doc_b").alias("u"), F.greatest("doc_a", "doc_b").alias("v")).where("u < v").distinct())

    def star(e: DataFrame, larger: bool) -> DataFrame:
        """Each node's neighbours (the larger ones, or the smaller ones and itself) linked to its smallest neighbour."""
        near = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v"))) if larger else e.select(F.col("v").alias("u"), F.col("u").alias("v"))
        low = near.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))
        near = near.join(low, "u")
        if larger:
            return near.where("v > u").select(F.col("low").alias("u"), "v").where("u < v").distinct()
        linked = near.select(F.col("low").alias("u"), "v").unionByName(low.select(F.col("low").alias("u"), F.col("u").alias("v")))
        return linked.where("u < v").distinct()

    state = None
    while True:
        links = cut_lineage(star(star(links, True), False))
        now = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if now == state:
            break
        state = now
    return links.groupBy(F.col("v").alias("doc_id")).agg(F.min("u").alias("group_id"))


def near_classes(docs: DataFrame, radius: int = RADIUS, confirm: int = CONFIRM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, class_id, n_links`` of every row of ``docs``.

    The class is the smallest id that near-duplicate pairs lead to, step by step, from the row's text; ``n_links``
    counts the other documents in a pair with it, those of its own fingerprints too, so no link is lost, but none is a row:
    the rows grow with the documents.  An id with several texts is a document for each of their fingerprints, and has a row
    for each row it has in ``docs``.

    Rows without an id, text or word are their own class and have no link.  A text of any length is read whole.  An empty
    table gives an empty table.  Other columns are ignored.
    """
    prints = cut_lineage(fingerprints(docs, id_col, text_col, whole=True))
    groups = prints.where("doc_id IS NOT NULL AND fp IS NOT NULL").groupBy("doc_id", "fp", "confirm").agg(F.count(F.lit(1)).alias("rows"))
    # an id that leads several groups would join them: groups are numbered, and the number turned into the least id afterwards
    folded = cut_lineage(groups.groupBy("fp", "confirm").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")).withColumn("doc_id", F.monotonically_increasing_id()))
    found = cut_lineage(near_fingerprints(folded, radius, confirm, forest=True, degrees=True))
    joined = components(found.where("doc_b IS NOT NULL")).withColumnRenamed("group_id", "lead")
    far = found.where("doc_b IS NULL").groupBy(F.col("doc_a").alias("doc_id")).agg(F.sum("distance").alias("far"))
    led = folded.join(joined, "doc_id", "left").withColumn("lead", F.coalesce("lead", "doc_id")).join(far, "doc_id", "left")
    least = led.groupBy("lead").agg(F.min("least").alias("class_id"))
    of = led.join(least, "lead").select("fp", "confirm", "class_id", (F.col("n") - 1 + F.coalesce("far", F.lit(0))).alias("n_links"))
    return prints.join(of, ["fp", "confirm"], "left").select("doc_id", F.when(F.col("doc_id").isNotNull(), F.coalesce("class_id", "doc_id")).alias("class_id"), F.when(F.col("doc_id").isNotNull(), F.coalesce("n_links", F.lit(0))).otherwise(0).cast("bigint").alias("n_links"))


def near_dedup(docs: DataFrame, radius: int = RADIUS, confirm: int = CONFIRM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` less all but the smallest id of each group that near-duplicate pairs connect.

    Rows without an id, text or word stay; so do rows that repeat the id that stays.  Texts of any
    length are read whole; an empty table gives an empty table.  Columns come back unchanged, whatever their names.
    """
    prints = cut_lineage(fingerprints(docs, id_col, text_col))
    folded = cut_lineage(fold(prints))
    groups = components(near_fingerprints(folded, radius, confirm, forest=True))
    lead = folded.join(groups, "doc_id", "left").select("fp", "confirm", F.coalesce("group_id", "doc_id").alias("lead"))
    gone, other = fresh(docs, "gone", "other")
    dropped = prints.join(lead, ["fp", "confirm"]).where("doc_id <> lead").select(F.col("doc_id").alias(gone)).distinct()
    return docs.join(dropped, F.col(f"`{id_col}`") == F.col(gone), "left_anti")
