"""Grouped prefix join on word shingles: all documents of Jaccard similarity 0.8 or more, as components.

A document is its set of distinct five-word shingles, held as 64-bit hashes.  Two
sets of that similarity share one of the first ``size - ceil(0.8 * size) + 1``
shingles in any common order; here the order is from rare to frequent, by a sketch
of the shingles' frequencies over all documents.  Documents with equal sizes and
equal prefixes are collapsed to one group.  Groups that meet under a shingle are
filtered by size and position, and by parities of the sets; pairs that are left are expanded to their members,
and members are verified on their whole sets.

What is asked for are components, so a link inside a component that is known
already need not be found again.  First turns compare a group with a few hubs
only, groups of the component that most groups under a shingle are in: as many
pairs as there are groups, however many of them share a shingle.  When that finds
few links, the last turn takes all pairs of groups under a shingle that are not
in one component, filters them, and expands what is left to members.  Its work
still grows with the pairs of groups that share a rare shingle and are in
different components; sizes, positions and parities rule out most of them in the
join.  Exact copies have one set and are one node throughout.  Nothing is capped:
every pair is linked, is in one component, or was ruled out by a filter that
loses nothing.

Null and empty texts have no shingle and are alone; fewer words than five are one
shingle; a very long text is one row of hashes at a time in a worker; repeated
rows, rows that share a doc_id and rows without one each have the component of
their text, whose component_id is the least doc_id in it (null if all are null);
other columns are ignored; an empty table gives an empty result.  Sets of equal
64-bit digest and size count as equal.  Sketches are of fixed size: beyond 2 ** 24
documents the order gets coarser and the lists are filtered less, which costs time, never links.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dgprop.llm.common import Scratch, documents, save, shuffle_partitions
from dgprop.llm.components import components
from dgprop.llm.textblocks import mix, shingle_sets

WIDTH = 5
#: Similarity as a fraction; 4/5 is 0.8.
OVER, UNDER = 4, 5
PARITIES = 4
PARITY = [f"parity{i}" for i in range(PARITIES)]
_BLOCK_BITS = 14
#: Shingles of a group that the first turns look at, from either end of its prefix, hubs of each shingle in a turn, pairs of each group in a turn, and turns at most.
LOOKED, HUBS, NEAREST, TURNS = 4, 32, 2, 2
#: The turns end when fewer than one pair in so many is a link.
LEAST_GAIN = 20
#: Rows under one shingle that are compared in one task.
SPLIT = 512
#: Shingles before one that its row remembers.
EARLIER = 4


def prefix_length(n: int) -> int:
    """Shingles of which similar sets must share one."""
    return n - -(-OVER * n // UNDER) + 1


def _sums(rows: DataFrame, partitions: int, combine: Callable[[np.ndarray, np.ndarray], np.ndarray], kind: str) -> DataFrame:
    """Blocks of arrays, combined by block: what a task holds is bounded by the blocks it is dealt."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for batch in batches:
            for b, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                new = np.frombuffer(v, kind)
                held[b] = combine(held[b], new) if b in held else new
        for b, v in held.items():
            yield pa.RecordBatch.from_pydict({"block": pa.array([b], pa.int32()), "cells": pa.array([v.tobytes()], pa.binary())})

    return rows.repartition(partitions, "block").mapInArrow(work, "block int, cells binary")


def _blocks(cells: np.ndarray, each: int) -> Iterator[pa.RecordBatch]:
    for b in range(0, len(cells), each):
        part = cells[b : b + each]
        if part.any():
            yield pa.RecordBatch.from_pydict({"block": pa.array([b // each], pa.int32()), "cells": pa.array([part.tobytes()], pa.binary())})


def frequency_levels(docs: DataFrame, bits: int) -> np.ndarray:
    """For each of ``2 ** bits`` cells eight times the binary logarithm of the shingles that fell in it.

    The size is fixed beforehand; more shingles in a cell make the order coarser, never wrong.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(1 << bits, np.uint32)
        shift = np.uint64(64 - bits)
        for batch in batches:
            held, size = [], 0
            for s in shingle_sets(batch.column("text"), WIDTH):
                held.append(s)
                size += len(s)
                if size > 1 << 18:
                    cells += np.bincount((np.concatenate(held) >> shift).astype(np.int64), minlength=len(cells)).astype(np.uint32)
                    held, size = [], 0
            if held:
                cells += np.bincount((np.concatenate(held) >> shift).astype(np.int64), minlength=len(cells)).astype(np.uint32)
        yield from _blocks(cells, 1 << _BLOCK_BITS)

    rows = docs.select("text").mapInArrow(work, "block int, cells binary")
    n_blocks = max(1, 1 << (bits - _BLOCK_BITS))
    wide = _sums(rows, min(n_blocks, shuffle_partitions(docs.sparkSession)), _add_capped, "<u4")
    levels = np.zeros(1 << bits, np.uint8)
    for r in wide.collect():  # of fixed size
        c = np.frombuffer(r["cells"], "<u4")
        at = r["block"] << _BLOCK_BITS
        levels[at : at + len(c)] = np.minimum(255, 8 * np.log2(1 + c.astype(np.float64))).astype(np.uint8)
    return levels


def _add_capped(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sums that stay at the greatest number."""
    return np.minimum(a.astype(np.uint64) + b, 0xFFFFFFFF).astype(np.uint32)


def membership(keys: DataFrame, column: str, bits: int) -> np.ndarray:
    """A bit array of ``2 ** bits`` places that has the place of every key; others may be set too."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        places = np.zeros(1 << bits, bool)
        for batch in batches:
            places[_place(batch.column(0).to_numpy(zero_copy_only=False), bits)] = True
        yield from _blocks(np.packbits(places), 1 << _BLOCK_BITS)

    rows = keys.select(column).mapInArrow(work, "block int, cells binary")
    out = np.zeros(max(1, (1 << bits) // 8), np.uint8)
    for r in _sums(rows, min(64, shuffle_partitions(keys.sparkSession)), np.bitwise_or, "u1").collect():  # of fixed size
        at, c = r["block"] << _BLOCK_BITS, np.frombuffer(r["cells"], np.uint8)
        out[at : at + len(c)] = c
    return out


def _holds(packed: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whether a bit array has the places of the keys."""
    place = _place(keys, len(packed).bit_length() + 2)
    return (packed[place >> 3] & (128 >> (place & 7)).astype(np.uint8)) != 0


def _place(keys: np.ndarray, bits: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return (mix(keys.astype(np.int64).view(np.uint64)) >> np.uint64(64 - bits)).astype(np.int64)


def _digest(hashes: np.ndarray, n: int, salt: int) -> int:
    """A 64-bit digest of a set of hashes and a number, as a signed integer."""
    with np.errstate(over="ignore"):
        total = mix(hashes ^ np.uint64(salt)).sum(dtype=np.uint64) + np.uint64(n * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        return int(mix(np.array([total], np.uint64)).view(np.int64)[0])


def parities(s: np.ndarray) -> np.ndarray:
    """For each of 256 cells whether an odd number of the set's hashes falls in it, as four 64-bit numbers.

    Sets differ in at least as many shingles as these bits differ.
    """
    with np.errstate(over="ignore"):
        cell = (mix(s) >> np.uint64(64 - 8)).astype(np.int64)
    return np.packbits((np.bincount(cell, minlength=64 * PARITIES) & 1).astype(bool)).view(np.int64)


class _Ordered:
    """Sets with their prefixes in the order from rare to frequent."""

    def __init__(self, levels: np.ndarray) -> None:
        self.levels, self.shift = levels, np.uint64(64 - (len(levels).bit_length() - 1))

    def prefix(self, s: np.ndarray) -> np.ndarray:
        level = self.levels[(s >> self.shift).astype(np.int64)]
        return s[np.argsort(level, kind="stable")[: prefix_length(len(s))]]


def set_rows(docs: DataFrame, levels) -> DataFrame:
    """doc_id, text_key, n_shingles, node (digest of the set), grp (digest of size and prefix) and the set's parities; nulls without shingles."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = _Ordered(levels.value)
        for batch in batches:
            n, node, grp, bits = [], [], [], []
            for s in shingle_sets(batch.column("text"), WIDTH):
                n.append(len(s))
                node.append(_digest(s, len(s), 1) if len(s) else None)
                grp.append(_digest(order.prefix(s), len(s), 2) if len(s) else None)
                bits.append(parities(s))
            parity = np.array(bits, np.int64).reshape(-1, PARITIES)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), *(pa.array(x, pa.int64()) for x in (n, node, grp, *parity.T))], ["doc_id", "text_key", "n_shingles", "node", "grp", *PARITY])

    return docs.select(F.col("doc_id").cast("bigint"), text_key().alias("text_key"), "text").mapInArrow(work, "doc_id bigint, text_key bigint, n_shingles bigint, node bigint, grp bigint, " + ", ".join(f"{c} bigint" for c in PARITY))


def postings(docs: DataFrame, levels, wanted=None) -> DataFrame:
    """h, grp, n, pos, looked: a group's prefix, once for each task; only shingles that ``wanted`` may hold.

    ``looked`` marks the rarest and the most frequent of the shingles that are left.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order, seen = _Ordered(levels.value), set()
        places = None if wanted is None else wanted.value
        for batch in batches:
            out: list[tuple[np.ndarray, int, int, np.ndarray]] = []
            for s in shingle_sets(batch.column("text"), WIDTH):
                if len(s):
                    p = order.prefix(s)
                    g = _digest(p, len(s), 2)
                    if g not in seen:
                        seen.add(g)
                        pos = np.arange(len(p))
                        h = p.view(np.int64)
                        if places is not None:
                            keep = _holds(places, h)
                            h, pos = h[keep], pos[keep]
                        out.append((h, g, len(s), pos))
            if out:
                sizes = [len(o[0]) for o in out]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.concatenate([o[0] for o in out]), pa.int64()),
                        pa.array(np.repeat(np.array([o[1] for o in out], np.int64), sizes)),
                        pa.array(np.repeat(np.array([o[2] for o in out], np.int32), sizes)),
                        pa.array(np.concatenate([o[3] for o in out]).astype(np.int32)),
                        pa.array(np.concatenate([(at < LOOKED) | (at >= k - LOOKED) for k in sizes for at in [np.arange(k)]])),
                    ],
                    ["h", "grp", "n", "pos", "looked"],
                )

    return docs.select("text").mapInArrow(work, "h bigint, grp bigint, n int, pos int, looked boolean")


def possible(a: str, b: str) -> Column:
    """Whether sizes and positions in the prefixes leave room for the similarity."""
    na, nb = F.col(f"{a}.n").cast("bigint"), F.col(f"{b}.n").cast("bigint")
    rest = F.least(na - F.col(f"{a}.pos"), nb - F.col(f"{b}.pos"))
    return near_sizes(a, b) & ((OVER + UNDER) * rest >= OVER * (na + nb))


def near_sizes(a: str, b: str) -> Column:
    na, nb = F.col(f"{a}.n").cast("bigint"), F.col(f"{b}.n").cast("bigint")
    return UNDER * F.least(na, nb) >= OVER * F.greatest(na, nb)


def parities_apart(a: str, b: str) -> Column:
    """In how many parities two sets differ, which is at most the number of shingles that only one of them has."""
    differ = [F.bit_count(F.col(f"{a}.{c}").bitwiseXOR(F.col(f"{b}.{c}"))) for c in PARITY]
    return sum(differ[1:], differ[0])


def near_parities(a: str, b: str) -> Column:
    """Whether the parities leave room for the similarity: sets that are similar differ in few shingles."""
    return (OVER + UNDER) * parities_apart(a, b) <= (UNDER - OVER) * (F.col(f"{a}.n") + F.col(f"{b}.n"))


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) of nodes whose whole sets are similar enough."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            left, right = batch.column("left_set"), batch.column("right_set")
            for i in range(batch.num_rows):
                x, y = np.frombuffer(left[i].as_buffer(), np.uint64), np.frombuffer(right[i].as_buffer(), np.uint64)
                both = np.concatenate((x, y))
                both.sort()
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(UNDER * shared >= OVER * (len(both) - shared))
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(pa.array(keep)), batch.column("b").filter(pa.array(keep))], ["a", "b"])

    one, two = sets.select(F.col("node").alias("a"), F.col("cells").alias("left_set")), sets.select(F.col("node").alias("b"), F.col("cells").alias("right_set"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "left_set", "right_set").mapInArrow(work, "a bigint, b bigint")


def sets_of(docs: DataFrame, wanted: DataFrame, bits: int, save: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    """node and its sorted set, written; ``wanted`` has node and the key of a text that has it.

    Texts are chosen by their key and told apart by the digest of their set, so rows
    that share a doc_id, or have none, are no matter.
    """
    places = docs.sparkSession.sparkContext.broadcast(membership(wanted, "text_key", bits))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = set()
        for batch in batches:
            rows = batch.filter(pa.array(_holds(places.value, batch.column("text_key").to_numpy(zero_copy_only=False))))
            for k in range(0, rows.num_rows, 256):
                node, cells = [], []
                for s in shingle_sets(rows.slice(k, 256).column("text"), WIDTH):
                    d = _digest(s, len(s), 1) if len(s) else None
                    if d is not None and d not in seen:
                        seen.add(d)
                        node.append(d)
                        cells.append(s.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(cells, pa.binary())], ["node", "cells"])

    made = docs.select(text_key().alias("text_key"), "text").mapInArrow(work, "node bigint, cells binary")
    found = save(made.join(wanted.select("node"), "node", "left_semi").dropDuplicates(["node"]), "sets")
    places.destroy()
    return found


def text_key() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def ends_of(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """node and text_key of the nodes in pairs (a, b)."""
    ends = pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct()
    return nodes.join(ends, "node", "left_semi").select("node", "text_key")


def ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct()


def star_pairs(lists: DataFrame, tested: DataFrame, turn: int) -> DataFrame:
    """Pairs of heads (a, b) that aren't tested yet: each with the nearest hubs of the part that most groups under a shingle are in.

    ``lists`` has h, n, node, part and parities.  Each shingle has at most
    ``HUBS`` hubs, others from turn to turn; each head is in at most ``NEAREST`` pairs as the one that looks.
    """
    busy = lists.join(lists.groupBy("h").agg(F.min("part").alias("x"), F.max("part").alias("y")).filter("x <> y").select("h"), "h", "left_semi")
    top = busy.groupBy("h", "part").agg(F.count("*").alias("groups")).groupBy("h").agg(F.max_by("part", F.struct("groups", "part")).alias("its_part"))
    drawn = Window.partitionBy("h").orderBy(F.xxhash64("node", F.lit(turn)), "node")
    hubs = busy.join(top, "h").filter("part = its_part").withColumn("_rank", F.row_number().over(drawn)).filter(F.col("_rank") <= HUBS)
    p, q = busy.alias("p"), hubs.alias("q")
    met = p.join(q, (F.col("p.h") == F.col("q.h")) & (F.col("p.part") != F.col("q.part")) & near_sizes("p", "q") & near_parities("p", "q"))
    near = met.groupBy(F.col("p.node").alias("node"), F.col("q.node").alias("hub")).agg(F.min(parities_apart("p", "q")).alias("apart"))
    near = near.withColumns({"a": F.least("node", "hub"), "b": F.greatest("node", "hub")}).join(tested, ["a", "b"], "left_anti")
    nearest = Window.partitionBy("node").orderBy("apart", F.xxhash64("hub"), "hub")
    return near.withColumn("_rank", F.row_number().over(nearest)).filter(F.col("_rank") <= NEAREST).select("a", "b").distinct()


def meeting(rows: DataFrame, key: str, own: str, condition: Column) -> DataFrame:
    """Pairs (p, q) of rows with the same key, each once, that meet the condition.

    A key of many rows is split: one side of each pair is dealt to blocks of about
    ``SPLIT`` rows, the other is sent to all blocks of the key.
    """
    size = rows.groupBy(key).agg(F.count("*").alias("_size")).filter("_size > 1").select(key, F.ceil(F.col("_size") / SPLIT).cast("int").alias("_blocks"))
    sized = rows.join(size, key)
    p = sized.withColumn("_block", F.pmod(F.xxhash64(own), F.col("_blocks")).cast("int")).alias("p")
    q = sized.withColumn("_block", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1))).alias("q")
    return p.join(q, (F.col(f"p.{key}") == F.col(f"q.{key}")) & (F.col("p._block") == F.col("q._block")) & (F.col(f"p.{own}") < F.col(f"q.{own}")) & condition)


def linked_components(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, n_shingles and component_id, the least doc_id that links reach, of every row."""
    spark = docs.sparkSession
    with Scratch(spark, "join") as scratch:
        return save(_linked(docs, scratch.save), "join-components")


def _linked(docs: DataFrame, save: Callable[[DataFrame, str], DataFrame]) -> DataFrame:
    context = docs.sparkSession.sparkContext
    n_docs = max(2, docs.count())
    bits = min(24, max(_BLOCK_BITS, math.ceil(math.log2(n_docs)) + 1))
    levels = context.broadcast(frequency_levels(docs, bits))
    rows = save(set_rows(docs, levels), "rows")
    nodes = save(
        rows.filter("n_shingles > 0").groupBy("node").agg(F.min("doc_id").alias("doc"), F.min("text_key").alias("text_key"), F.min("grp").alias("grp"), F.min("n_shingles").cast("int").alias("n"), *[F.min(c).alias(c) for c in PARITY]), "nodes"
    )

    # Shingles in whose lists two groups meet, then these lists.
    met = postings(docs, levels).groupBy("h").agg(F.min("grp").alias("x"), F.max("grp").alias("y")).filter("x <> y").select("h")
    met = save(met, "met")
    place_bits = min(28, max(17, math.ceil(math.log2(n_docs)) + 8))
    wanted = context.broadcast(membership(met, "h", place_bits))
    lists = postings(docs, levels, wanted).groupBy("h", "grp").agg(F.min("n").alias("n"), F.min("pos").alias("pos"), F.max("looked").alias("looked"))
    lists = save(lists.join(met, "h", "left_semi"), "lists")

    # Members of a group with its head, and heads with hubs, as long as that links many of them.
    groups = nodes.groupBy("grp").agg(F.min("node").alias("head"), F.count("*").alias("members"))
    several = save(nodes.join(groups.filter("members > 1"), "grp"), "several")
    in_play = save(nodes.join(lists.select("grp").union(several.select("grp")).distinct(), "grp", "left_semi"), "in-play")
    heads = in_play.groupBy("grp").agg(F.min_by(F.struct("node", *PARITY), "node").alias("head")).select("grp", "head.*")
    looked = save(lists.filter("looked").drop("looked", "pos").join(heads, "grp"), "looked")
    own = ordered(several.select(F.col("node").alias("a"), F.col("head").alias("b")))
    tested = sets = roots = None
    for turn in range(TURNS):
        if roots is None:
            pairs = save(star_pairs(looked.withColumn("part", F.col("node")), own, turn).union(own), "pairs")
            tested, sets = pairs, sets_of(docs, ends_of(pairs, nodes), place_bits, save)
        else:
            part = looked.join(roots.withColumnRenamed("root", "part"), "node", "left").withColumn("part", F.coalesce("part", "node"))
            pairs = save(star_pairs(part, tested, turn), "pairs")
            others = ends_of(pairs, nodes).join(sets.select("node"), "node", "left_anti")
            tested, sets = tested.union(pairs), sets.unionByName(sets_of(docs, others, place_bits, save))
        more = save(verified(pairs, sets), "links")
        roots = components(more if roots is None else roots.select(F.col("node").alias("a"), F.col("root").alias("b")).union(more), save)
        if more.count() * LEAST_GAIN <= pairs.count():
            break

    # Groups that meet under a shingle and aren't all in one component, then their members.
    part = save(in_play.join(roots.withColumnRenamed("root", "part"), "node", "left").withColumn("part", F.coalesce("part", "node")), "parts")
    alone = [F.when(F.count("*") == 1, F.min(c)).alias(c) for c in PARITY]
    state = part.groupBy("grp").agg(F.min("part").alias("low"), F.max("part").alias("high"), *alone)
    spread = lists.select("h", "grp", "n", "pos").join(state, "grp")
    mixed = spread.groupBy("h").agg(F.min("low").alias("x"), F.max("high").alias("y")).filter("x <> y").select("h")
    # A pair that met under a shingle before this one need not meet again; a few shingles before tell mostly.
    in_order = Window.partitionBy("grp").orderBy("pos")
    still = spread.join(mixed, "h", "left_semi").withColumn("earlier", F.array(*[F.lag("h", k).over(in_order) for k in range(1, EARLIER + 1)]))
    still = save(still.withColumn("earlier", F.array_compact("earlier")), "still")
    first = ~F.arrays_overlap("p.earlier", "q.earlier")
    apart = (F.col("p.low") != F.col("q.low")) | (F.col("p.low") != F.col("p.high")) | (F.col("q.low") != F.col("q.high"))
    across = save(meeting(still, "h", "grp", apart & possible("p", "q") & F.coalesce(near_parities("p", "q"), F.lit(True)) & first).select(F.col("p.grp").alias("g1"), F.col("q.grp").alias("g2")).distinct(), "group-pairs")
    one, two = (part.select(F.col("grp").alias(g), F.struct("node", "part", "n", *PARITY).alias(s)) for g, s in (("g1", "p"), ("g2", "q")))
    unlike = (F.col("p.part") != F.col("q.part")) & near_parities("p", "q")
    between = across.join(one, "g1").join(two, "g2").filter(unlike).select(F.col("p.node").alias("a"), F.col("q.node").alias("b"))
    inside = meeting(part.join(several.select("node"), "node", "left_semi"), "grp", "node", unlike).select(F.col("p.node").alias("a"), F.col("q.node").alias("b"))
    rest = save(ordered(between.union(inside)).join(tested, ["a", "b"], "left_anti"), "rest")
    others = ends_of(rest, nodes).join(sets.select("node"), "node", "left_anti")
    more = save(verified(rest, sets.unionByName(sets_of(docs, others, place_bits, save))), "links")
    roots = components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).union(more), save)

    least = nodes.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    by_root = least.groupBy("root").agg(F.min("doc").alias("component_id"))
    known = least.join(by_root, "root").select("node", "root", "component_id")
    levels.destroy()
    wanted.destroy()
    found = rows.select("doc_id", "text_key", "n_shingles", "node").join(known, "node", "left")
    return found.select("doc_id", "text_key", "n_shingles", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "root")


def one_of_each(docs: DataFrame) -> DataFrame:
    """One row of ``docs`` for each component: the one of the least doc_id, and of rows that share it the one of the least text_key.

    Rows without shingles are alone, each text of a doc_id for itself.  Of rows with
    equal doc_id and text one is kept; a row without doc_id goes for any other of its component.
    """
    rows = linked_components(docs)
    row = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col("text_key"))
    linked = rows.filter("root IS NOT NULL").groupBy("root").agg(F.min(row).alias("row")).select("row.doc_id", "row.text_key")
    keep = linked.union(rows.filter("root IS NULL").select("doc_id", "text_key")).distinct()
    key = [F.coalesce("doc_id", F.lit(-(1 << 62))).alias("_doc"), F.col("doc_id").isNull().alias("_none")]
    keyed = docs.select("*", *key, text_key().alias("_text_key"))
    kept = keyed.join(keep.select(*key, F.col("text_key").alias("_text_key")), ["_doc", "_none", "_text_key"], "left_semi")
    return kept.dropDuplicates(["_doc", "_none", "_text_key"]).select(*docs.columns)


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linked_components(documents(spark, sf_dir)).select("doc_id", "n_shingles", "component_id")
