"""Packing documents into sequences by bin completion with branch and bound.

Pieces are dealt to groups of a bounded number of rows, about, by the place where
a task made them (so that equal or missing ids are no matter), and each group is
packed on its own.  In a group, the bin of the largest piece left is
completed first; the fillings that no other filling dominates are tried in the
order of their waste; a branch ends when the waste so far can't give fewer bins
than the best packing known.  Best fit decreasing is the first such packing.  If
it meets the lower bound it is optimal, and nothing is searched.  The search ends
when the bound is met or after ``max_nodes`` bins, keeping the best one found; its
limits bound the time of a group, never what is packed.

Documents longer than a sequence are cut into full pieces and a rest; full
pieces are sequences of their own.  Null and empty texts are one end id.  Rows
with equal or no doc_id are packed each for itself; pieces of one length are taken
in the order of their rows; a very long text is encoded whole, one at a time in a
worker; other columns are ignored; an empty table gives no pieces.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right, insort
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.llm.common import documents, parts_for, save, text_rows
from dgprop.llm.tokens import encoder

CAPACITY = 4096
#: Pieces of one group; a task holds one group at a time.
GROUP_ROWS = 20_000
#: Bins that the search may complete beyond the first packing, for each group.
MAX_NODES = 5_000
#: Fillings that are compared for one bin, and steps for each that the search for them may take.
MAX_FILLINGS, LOOKS = 32, 8
_PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"
#: Rows that follow each other in a task and go to one group.
DEALT = 64


def pieces_of(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = 1) -> DataFrame:
    """One row for each piece of each document, with its place in the document's ids; ``place`` is that of the row in its task."""
    end = end_id.to_bytes(4, "little")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, made = TaskContext.get().partitionId(), 0
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                rows = batch.slice(k, 512)
                out: list[tuple] = []
                for doc, coded in zip(rows.column("doc_id").to_pylist(), encoder(vocabulary).encode(rows.column("text").to_pylist()), strict=True):
                    ids = coded + end
                    for p, at in enumerate(range(0, len(ids), 4 * capacity)):
                        part = ids[at : at + 4 * capacity]
                        out.append((doc, p, at // 4, len(part) // 4, zlib.crc32(part)))
                columns = [*zip(*out, strict=True), [task << 40 | (made + i) // DEALT for i in range(len(out))]]
                made += len(out)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if i == 1 else pa.int64()) for i, c in enumerate(columns)], ["doc_id", "piece", "start", "length", "ids_crc32", "place"])

    return text_rows(docs).mapInArrow(work, f"{_PIECES}, place bigint")


def best_fit_decreasing(lengths: list[int], capacity: int) -> list[list[int]]:
    """Each piece, largest first, goes to the fullest bin that takes it; bins of indices."""
    bins: list[list[int]] = []
    room: list[tuple[int, int]] = []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        k = bisect_right(room, (lengths[i] - 1, len(lengths)))
        if k == len(room):
            bins.append([i])
            insort(room, (capacity - lengths[i], len(bins) - 1))
        else:
            left, b = room.pop(k)
            bins[b].append(i)
            insort(room, (left - lengths[i], b))
    return bins


def lower_bound(lengths: list[int], capacity: int) -> int:
    """Bins that any packing needs: by the sum, and by the pieces of more than half a bin with what can't lie beside them."""
    n = np.sort(np.asarray(lengths, np.int64))
    if not len(n):
        return 0
    sums = np.concatenate(([0], np.cumsum(n)))
    least = -(-int(sums[-1]) // capacity)
    for k in {0, *n[n <= capacity // 2].tolist()}:
        small, half, large = np.searchsorted(n, [k, capacity // 2 + 1, capacity - k + 1])
        between, room = int(sums[half] - sums[small]), int((large - half) * capacity - (sums[large] - sums[half]))
        least = max(least, int(len(n) - half) + max(0, -(-(between - room) // capacity)))
    return least


def fillings(first: int, sizes: list[int], counts: dict[int, int], capacity: int, limit: int) -> list[list[int]]:
    """Undominated fillings of a bin around ``first``, least waste first.

    A filling is dominated if another piece that is left fits as well, or if one of
    its pieces can be exchanged for a larger one that is left.  ``sizes`` are the
    distinct sizes left, ascending.  The search for fillings goes from large pieces
    to small ones and ends with ``limit`` of them, or after ``LOOKS * limit`` steps;
    the filling that always takes the largest piece comes first and is always found.
    """
    found: list[tuple[int, list[int]]] = []
    used: dict[int, int] = {}
    looked = 0

    def full() -> bool:
        return len(found) >= limit or (bool(found) and looked > LOOKS * limit)

    def grow(room: int, end: int, taken: list[int]) -> None:
        nonlocal looked
        looked += 1
        for k in range(min(end, bisect_right(sizes, room)) - 1, -1, -1):
            s = sizes[k]
            for m in range(min(counts[s], room // s), 0, -1):
                used[s] = m
                grow(room - m * s, k, taken + [s] * m)
                del used[s]
                if full():
                    return
        if not _better(taken, room, sizes, counts, used):
            found.append((room, taken))

    grow(capacity - first, len(sizes), [])
    return [taken for _, taken in sorted(found, key=lambda f: f[0])]


def _better(taken: list[int], room: int, sizes: list[int], counts: dict[int, int], used: dict[int, int]) -> bool:
    """Whether a piece that is left fits too, or can take the place of a smaller one."""
    for s in {0, *taken}:
        for k in range(bisect_right(sizes, s), bisect_right(sizes, s + room)):
            if counts[sizes[k]] > used.get(sizes[k], 0):
                return True
    return False


def bin_completion(lengths: list[int], capacity: int = CAPACITY, max_nodes: int = MAX_NODES, max_fillings: int = MAX_FILLINGS) -> list[list[int]]:
    """The packing with the fewest bins that the search finds, as lists of indices; it is optimal if no limit was met."""
    incumbent = best_fit_decreasing(lengths, capacity)
    total = sum(lengths)
    bound = lower_bound(lengths, capacity)
    if len(incumbent) <= bound:
        return incumbent
    counts: dict[int, int] = {}
    for n in lengths:
        counts[n] = counts.get(n, 0) + 1
    sizes = sorted(counts)
    best: list[list[int]] | None = None
    best_bins, nodes = len(incumbent), 0

    def take(filling: list[int], sign: int) -> None:
        for s in filling:
            counts[s] -= sign
            if counts[s] == 0 and sign > 0:
                sizes.remove(s)
            elif counts[s] == 1 and sign < 0:
                insort(sizes, s)

    chosen: list[list[int]] = []
    waste = 0
    stack: list[Iterator[list[int]]] = []

    def options() -> Iterator[list[int]]:
        first = sizes[-1]
        counts[first] -= 1
        if counts[first] == 0:
            sizes.pop()
        got = fillings(first, sizes, counts, capacity, max_fillings)
        counts[first] += 1
        if counts[first] == 1:
            insort(sizes, first)
        return iter([[first, *f] for f in got])

    stack.append(options())
    while stack and nodes < max_nodes + len(incumbent) and best_bins > bound:
        filling = next(stack[-1], None)
        if filling is None:
            stack.pop()
            if chosen:
                last = chosen.pop()
                take(last, -1)
                waste -= capacity - sum(last)
            continue
        more = capacity - sum(filling)
        # k bins hold k * capacity, so waste beyond this can't give fewer than the best.
        if waste + more > (best_bins - 1) * capacity - total:
            continue
        nodes += 1
        take(filling, 1)
        chosen.append(filling)
        waste += more
        if not sizes:
            best, best_bins = [list(c) for c in chosen], len(chosen)
            last = chosen.pop()
            take(last, -1)
            waste -= capacity - sum(last)
        else:
            stack.append(options())
    if best is None:
        return incumbent
    places: dict[int, list[int]] = {}
    for i, n in enumerate(lengths):
        places.setdefault(n, []).append(i)
    return [[places[s].pop() for s in b] for b in best]


def pack(pieces: DataFrame, capacity: int = CAPACITY, group_rows: int = GROUP_ROWS) -> DataFrame:
    """Add sequence_id and offset to the pieces, which have to be a table that is written: ``place`` deals them to groups."""
    n_groups = parts_for(pieces.count(), group_rows)
    schema = f"{_PIECES}, sequence_id bigint, offset bigint"

    def work(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["place", "doc_id", "piece", "ids_crc32"], kind="stable", ignore_index=True)
        lengths = rows["length"].to_numpy()
        sequence, offset = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
        full = np.flatnonzero(lengths >= capacity)
        sequence[full] = np.arange(len(full))
        open_rows = np.flatnonzero(lengths < capacity)
        for b, members in enumerate(bin_completion(lengths[open_rows].tolist(), capacity), len(full)):
            at = 0
            for i in members:
                sequence[open_rows[i]], offset[open_rows[i]] = b, at
                at += int(lengths[open_rows[i]])
        rows["sequence_id"], rows["offset"] = (int(key[0]) << 32) + sequence, offset
        return rows[["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]]

    dealt = pieces.withColumn("pack_group", F.pmod(F.xxhash64("place"), F.lit(n_groups)))
    return dealt.groupBy("pack_group").applyInPandas(work, schema)


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = 1, group_rows: int = GROUP_ROWS) -> DataFrame:
    return pack(save(pieces_of(docs, vocabulary, capacity, end_id), "pieces"), capacity, group_rows)


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
