"""Context-tree weighting of bytes, learnt from a corpus and applied to all of it.

A text is its words, A to Z lower-cased, with one space between them and an end
byte.  Each byte is eight binary decisions; each decision has a tree of contexts of
0 to ``DEPTH`` bytes before.  A node estimates its decision by Krichevsky and
Trofimov's rule and weighs that, half and half, against the product of its
children; the weights after the training texts mix all depths into one probability.
The score of a text is the logarithm of its probability, so -log2 of it over its
bytes is the code length per byte.

The corpus is cut into blocks.  Every block sends the distinct contexts-with-byte
and words it has, with their counts in training texts, to shards.  A shard adds
them up as they come and holds each distinct one once, whole subtrees below two
bytes of context, whose nodes it makes piece by piece; it answers every block, one
request at a time, with the probabilities it asked for.  Only the nodes above, at
most 256 * 255 of them, come to the driver.  The subtree of the most frequent pair
of bytes is not divided: the memory of a shard is at least 24 bytes for each
distinct context-with-byte in it.  The counts cover all training texts, and what
is kept grows with them.  A word unigram score with additive smoothing is worked
out on the way by the same exchange.

Null and empty texts are the end byte alone; repeated rows, and rows without
doc_id, are scored each for itself; a very long text is a slice of its own; other
columns are ignored; equal keys are added up, so ties don't occur; an empty table
gives an empty result; without training texts all estimates are even.  Words are
told apart by a 63-bit hash, and the logarithm of a byte's probability is sent as
a 32-bit number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.llm.common import documents, parts_for, save, shuffle_partitions
from dgprop.llm.textblocks import LOWER, mix, slices, word_hashes, word_spans

DEPTH = 6
#: Context bytes that decide on the shard; the driver sums up the nodes of fewer.
TOP = 2
END = 10
#: Bytes of text in a block, about; of a file's part, its bytes on disk.
BLOCK_BYTES = 16 << 20
#: Keys in one row that is sent, and keys whose nodes are made at a time.
ROW_KEYS, PIECE_KEYS = 1 << 16, 1 << 16
_SENT = "block bigint, shard int, kind int, at int, keys binary, counts binary"
_MERGE_AT = 1 << 22


def packed(values: np.ndarray) -> bytes:
    """Numbers as bytes, first bytes first: sorted 64-bit keys by their differences, others as they are."""
    if values.dtype == np.uint64:
        values = np.diff(values, prepend=np.uint64(0))
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(-1, values.itemsize).T)
    return zstandard.compress(planes.tobytes(), 1)


def unpacked(data: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(data), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    values = np.ascontiguousarray(planes.T).view(kind).reshape(-1)
    return np.cumsum(values, dtype=np.uint64) if kind == np.uint64 else values


def byte_stream(data: np.ndarray, off: np.ndarray, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, tuple]:
    """The texts as one stream, each after ``depth`` end bytes; which places are symbols; each text's first place; word spans."""
    starts, ends, row = word_spans(data, off)
    n = len(off) - 1
    words = np.bincount(row, minlength=n)
    letters = np.bincount(row, weights=ends - starts, minlength=n).astype(np.int64)
    length = depth + letters + np.maximum(words, 1)
    first = np.concatenate(([0], np.cumsum(length)))
    out = np.full(first[-1], 32, np.uint8)
    symbol = np.ones(first[-1], bool)
    for k in range(depth):
        out[first[:-1] + k], symbol[first[:-1] + k] = END, False
    out[first[1:] - 1] = END
    if len(starts):
        size = ends - starts
        in_text = np.cumsum(size + 1) - (size + 1)
        before = np.concatenate(([0], np.cumsum(letters + words)))[:-1]
        place = first[row] + depth + in_text - before[row]
        inside = np.repeat(place - np.concatenate(([0], np.cumsum(size)))[:-1], size) + np.arange(size.sum())
        source = np.repeat(starts - np.concatenate(([0], np.cumsum(size)))[:-1], size) + np.arange(size.sum())
        out[inside] = LOWER[data[source]]
    return out, symbol, first, (starts, ends, row)


def context_keys(stream: np.ndarray, symbol: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """For every symbol its context, latest byte first, and then itself, as one number."""
    s = stream.astype(np.uint64)
    key = np.zeros(max(0, len(s) - depth), np.uint64)
    for k in range(1, depth + 1):
        key = key << np.uint64(8) | s[depth - k : len(s) - k]
    return (key << np.uint64(8) | s[depth:])[symbol[depth:]]


class _Tally:
    """Distinct keys with their counts, where a key's lowest bit says whether its count is asked for."""

    def __init__(self) -> None:
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.size = 0

    def add(self, keys: np.ndarray, counted: np.ndarray) -> None:
        k = np.sort(keys << np.uint64(1) | counted.astype(np.uint64))
        if len(k):
            at = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
            self.parts.append((k[at], np.diff(np.append(at, len(k)))))
            self.size += len(at)
            if self.size > _MERGE_AT:
                self._merge()

    def _merge(self) -> None:
        if self.parts:
            self.parts = [summed(np.concatenate([p[0] for p in self.parts]), np.concatenate([p[1] for p in self.parts]))]
            self.size = len(self.parts[0][0]) // 2

    def result(self) -> tuple[np.ndarray, np.ndarray]:
        """Keys, sorted, and their counts where counted (else zero)."""
        if not self.parts:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self._merge()
        k, n = self.parts[0]
        return summed(k >> np.uint64(1), np.where(k & np.uint64(1), n, 0))


def summed(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, sorted, with the sums of their values."""
    if len(keys) == 0:
        return keys, values
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    at = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
    return k[at], np.add.reduceat(values[order], at)


def block_keys(texts: pa.Array, trained: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """The distinct words and contexts-with-byte of the texts, with their counts in training texts."""
    tallies = [_Tally(), _Tally()]
    for first, end, data, off in slices(texts):
        stream, symbol, start, spans = byte_stream(data, off)
        use = trained[first:end]
        tallies[0].add(word_hashes(data, spans[0], spans[1]) >> np.uint64(1), use[spans[2]])
        place = np.repeat(np.arange(end - first), np.diff(start))[symbol]
        tallies[1].add(context_keys(stream, symbol), use[place])
    return [t.result() for t in tallies]


def shard_of(keys: np.ndarray, kind: int, shards: int) -> np.ndarray:
    """Contexts with the same two latest bytes go together."""
    return (mix(keys >> np.uint64(8 * (DEPTH + 1 - TOP)) if kind else keys) % np.uint64(shards)).astype(np.int64)


def _log_gamma(x: np.ndarray) -> np.ndarray:
    """The logarithm of the gamma function for x > 0, by Stirling's series after a shift by 8."""
    low = np.zeros_like(x)
    for k in range(8):
        low += np.log(x + k)
    y = x + 8
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - 1 / (1680 * y**7) - low


def log_estimate(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """Logarithm of Krichevsky and Trofimov's estimate of a sequence with these counts."""
    return _log_gamma(n0 + 0.5) + _log_gamma(n1 + 0.5) - _log_gamma(n0 + n1 + 1.0) - np.log(np.pi)


_SMALL = 64
_SMALL_ESTIMATES = log_estimate(*np.meshgrid(np.arange(_SMALL, dtype=float), np.arange(_SMALL, dtype=float), indexing="ij"))


def log_estimates(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """The same, where most counts are small whole numbers."""
    out = _SMALL_ESTIMATES[np.minimum(n0, _SMALL - 1).astype(np.int64), np.minimum(n1, _SMALL - 1).astype(np.int64)]
    large = np.maximum(n0, n1) >= _SMALL
    out[large] = log_estimate(n0[large], n1[large])
    return out


class _Nodes:
    """The nodes of one depth for one of the eight decisions, in the order of their keys (context, bits so far)."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray, j: int) -> None:
        key = keys >> np.uint64(8 - j)
        new = np.concatenate((np.ones(min(1, len(key)), bool), key[1:] != key[:-1]))
        at = np.flatnonzero(new)
        self.bit = (keys >> np.uint64(7 - j) & np.uint64(1)).astype(bool)
        self.keys = key[at]
        self.of = np.cumsum(new) - 1
        n = counts.astype(float)
        self.n1 = np.add.reduceat(np.where(self.bit, n, 0), at) if len(at) else n[:0]
        self.n0 = (np.add.reduceat(n, at) if len(at) else n[:0]) - self.n1
        self.log_own = log_estimates(self.n0, self.n1)
        self.log_mixed = self.log_own

    def mix_with(self, log_children: np.ndarray) -> None:
        self.log_mixed = np.log(0.5) + np.logaddexp(self.log_own, log_children)

    def chance(self) -> np.ndarray:
        """For each key the estimate of its bit."""
        n1, n = self.n1[self.of], (self.n0 + self.n1)[self.of]
        return (np.where(self.bit, n1, n - n1) + 0.5) / (n + 1)

    def own_share(self) -> np.ndarray:
        return np.exp(np.log(0.5) + self.log_own - self.log_mixed)


def _parent_keys(keys: np.ndarray, bits: int) -> np.ndarray:
    """Keys without their farthest context byte, which stands above the ``bits`` lowest."""
    low = np.uint64((1 << bits) - 1)
    return keys >> np.uint64(bits + 8) << np.uint64(bits) | keys & low


class _Piece:
    """All nodes of depths ``TOP + 1`` to ``DEPTH`` over keys that share no such node with others, weighted from below."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray) -> None:
        tables = {DEPTH: (keys, counts)}
        for d in range(DEPTH - 1, TOP, -1):
            tables[d] = summed(_parent_keys(tables[d + 1][0], 8), tables[d + 1][1])
        self.tables = tables
        self.levels = {d: [_Nodes(*tables[d], j) for j in range(8)] for d in tables}
        for d in range(DEPTH - 1, TOP, -1):
            for j in range(8):
                mine, below = self.levels[d][j], self.levels[d + 1][j]
                place = np.searchsorted(mine.keys, _parent_keys(below.keys, j))
                mine.mix_with(np.bincount(place, weights=below.log_mixed, minlength=len(mine.keys)))

    def above(self) -> list[np.ndarray]:
        """For the nodes one byte up: context, node (1 to 255), n0, n1, sum of the logarithms of these nodes."""
        out: list[list[np.ndarray]] = [[], [], [], [], []]
        for j, nodes in enumerate(self.levels[TOP + 1]):
            up, place = np.unique(_parent_keys(nodes.keys, j), return_inverse=True)
            out[0].append((up >> np.uint64(j)).astype(np.int64))
            out[1].append((up & np.uint64((1 << j) - 1)).astype(np.int64) | 1 << j)
            for o, w in zip(out[2:], (nodes.n0, nodes.n1, nodes.log_mixed), strict=True):
                o.append(np.bincount(place, weights=w, minlength=len(up)))
        return [np.concatenate(o) for o in out]

    def chances(self) -> list[np.ndarray]:
        """For each decision and key the probability of its bit by these depths."""
        rows = {DEPTH: np.arange(len(self.tables[DEPTH][0]))}
        for d in range(DEPTH - 1, TOP, -1):
            rows[d] = np.searchsorted(self.tables[d][0], _parent_keys(self.tables[d + 1][0], 8))[rows[d + 1]]
        out = []
        for j in range(8):
            p = self.levels[DEPTH][j].chance()
            for d in range(DEPTH - 1, TOP, -1):
                nodes, r = self.levels[d][j], rows[d]
                share = nodes.own_share()[nodes.of][r]
                p = share * nodes.chance()[r] + (1 - share) * p
            out.append(p)
        return out


class Subtrees:
    """The subtrees below ``TOP`` bytes of context over the given sorted keys; ``middle`` are the sums for their roots, if known."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray, middle: list[np.ndarray] | None = None) -> None:
        self.keys, self.counts = keys, counts
        if middle is None:
            parts = [_Piece(keys[a:b], counts[a:b]).above() for a, b in self._pieces()]
            middle = [np.concatenate(c) for c in zip(*parts, strict=True)] if parts else [np.zeros(0, np.int64)] * 2 + [np.zeros(0)] * 3
        self.middle = middle
        self.contexts = np.unique(middle[0])
        at = (np.searchsorted(self.contexts, middle[0]), middle[1])
        self.n0, self.n1, below = np.zeros((3, len(self.contexts), 256))
        for table, values in zip((self.n0, self.n1, below), middle[2:], strict=True):
            np.add.at(table, at, values)
        self.log_own = log_estimates(self.n0, self.n1)
        self.log_mixed = np.log(0.5) + np.logaddexp(self.log_own, below)

    def _pieces(self) -> Iterator[tuple[int, int]]:
        """Ranges of about ``PIECE_KEYS`` keys, cut between contexts of ``TOP + 1`` bytes."""
        root, a = self.keys >> np.uint64(8 * (DEPTH - TOP)), 0
        while a < len(root):
            last = root[min(a + PIECE_KEYS, len(root)) - 1]
            b = int(np.searchsorted(root, last))
            b = len(root) if a + PIECE_KEYS >= len(root) else b if b > a else int(np.searchsorted(root, last, "right"))
            yield a, b
            a = b

    def summary(self) -> tuple[np.ndarray, ...]:
        """For the nodes one byte up: latest byte, node (1 to 255), n0, n1, sum of the logarithms of these nodes."""
        used = np.unique(np.searchsorted(self.contexts, self.middle[0]) * 256 + self.middle[1])
        context, node = used // 256, used % 256
        up, place = np.unique((self.contexts[context] >> 8) * 256 + node, return_inverse=True)
        sums = [np.bincount(place, weights=t.reshape(-1)[used], minlength=len(up)) for t in (self.n0, self.n1, self.log_mixed)]
        return up // 256, up % 256, *sums

    def log_chances(self, top: TopNodes) -> np.ndarray:
        """For each key the logarithm of the probability of its byte after its context."""
        out = np.zeros(len(self.keys))
        share2 = np.exp(np.log(0.5) + self.log_own - self.log_mixed)
        one2 = (self.n1 + 0.5) / (self.n0 + self.n1 + 1)
        for a, b in self._pieces():
            keys = self.keys[a:b]
            symbol = (keys & np.uint64(255)).astype(np.int64)
            row = np.searchsorted(self.contexts, (keys >> np.uint64(8 * (DEPTH + 1 - TOP))).astype(np.int64))
            latest = (keys >> np.uint64(8 * DEPTH)).astype(np.int64)
            total = np.zeros(b - a)
            for j, p in enumerate(_Piece(keys, self.counts[a:b]).chances()):
                node, bit = symbol >> (8 - j) | 1 << j, symbol >> (7 - j) & 1
                for share, one in ((share2[row, node], one2[row, node]), (top.share1[latest, node], top.one1[latest, node]), (top.share0[node], top.one0[node])):
                    p = share * np.where(bit, one, 1 - one) + (1 - share) * p
                total += np.log(p)
            out[a:b] = total
        return out


class TopNodes:
    """Depths 0 and 1: for each node the share of its own estimate, and its estimate of a one."""

    def __init__(self, latest: np.ndarray, node: np.ndarray, n0: np.ndarray, n1: np.ndarray, log_below: np.ndarray) -> None:
        counts, below = np.zeros((2, 256, 256)), np.zeros((256, 256))
        for c, n in zip(counts, (n0, n1), strict=True):
            np.add.at(c, (latest, node), n)
        np.add.at(below, (latest, node), log_below)
        own = log_estimate(counts[0], counts[1])
        # A node that no text has is worth 1 either way, as are its children.
        mixed = np.log(0.5) + np.logaddexp(own, below)
        self.share1, self.one1 = np.exp(np.log(0.5) + own - mixed), (counts[1] + 0.5) / (counts.sum(0) + 1)
        root = counts.sum(1)
        own = log_estimate(root[0], root[1])
        mixed_root = np.log(0.5) + np.logaddexp(own, mixed.sum(0))
        self.share0, self.one0 = np.exp(np.log(0.5) + own - mixed_root), (root[1] + 0.5) / (root.sum(0) + 1)


def with_blocks(docs: DataFrame, training: Column) -> DataFrame:
    """block, doc_id, text, trained; blocks are in the parts of files that tasks read, or hashes of rows where there are none."""
    row = F.xxhash64("doc_id", "text")
    if docs.inputFiles():
        deal = F.pmod(row, F.greatest(F.lit(1), F.ceil(F.input_file_block_length() / BLOCK_BYTES)))
        block: Column = F.xxhash64(F.input_file_name(), F.input_file_block_start(), deal)
    else:
        total = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).head()[0]
        n = max(shuffle_partitions(docs.sparkSession), parts_for(total, BLOCK_BYTES))
        block = F.pmod(row, F.lit(n)).cast("bigint")
    return docs.select(block.alias("block"), "doc_id", F.coalesce("text", F.lit("")).alias("text"), training.alias("trained"))


def send_keys(rows: DataFrame, shards: int) -> DataFrame:
    """What every block asks of every shard: keys in order, and their counts in training texts."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            blocks = batch.column("block").to_numpy()
            trained = batch.column("trained").to_numpy(zero_copy_only=False)
            for b in np.unique(blocks).tolist():
                mine = pa.array(blocks == b)
                part = [_Tally(), _Tally()] if b not in held else held[b]
                held[b] = part
                texts, use = batch.column("text").filter(mine), trained[blocks == b]
                for t, (keys, counts) in zip(part, block_keys(texts, use), strict=True):
                    for flag in (0, 1):
                        at = (counts > 0) == bool(flag)
                        if at.any():
                            t.parts.append((keys[at] << np.uint64(1) | np.uint64(flag), np.maximum(counts[at], 1)))
                            t.size += int(at.sum())
                    if t.size > _MERGE_AT:
                        t._merge()
        for b, tallies in held.items():
            for kind, t in enumerate(tallies):
                keys, counts = t.result()
                shard = shard_of(keys, kind, shards)
                order = np.argsort(shard, kind="stable")
                bounds = np.searchsorted(shard[order], np.arange(shards + 1))
                for s in np.flatnonzero(np.diff(bounds)).tolist():
                    for n, k in enumerate(range(bounds[s], bounds[s + 1], ROW_KEYS)):
                        at = order[k : min(k + ROW_KEYS, bounds[s + 1])]
                        yield pa.RecordBatch.from_pydict({"block": pa.array([b], pa.int64()), "shard": pa.array([s], pa.int32()), "kind": pa.array([kind], pa.int32()), "at": pa.array([n], pa.int32()), "keys": pa.array([packed(keys[at])], pa.binary()), "counts": pa.array([packed(counts[at].astype(np.uint32))], pa.binary())})

    from_files = bool(rows.inputFiles())
    return (rows if from_files else rows.repartition("block")).mapInArrow(work, _SENT)


_MERGED = "shard int, kind int, part int, keys binary, counts binary, latest int, node int, n0 double, n1 double, below double"


def _merged_rows(shard: int, kind: int, keys: np.ndarray, counts: np.ndarray) -> Iterator[pa.RecordBatch]:
    """A shard's sums: its table in rows (part 1), the sums for the roots of its subtrees (part 0) and those for the driver (part 2)."""

    def rows(part: int, **columns: list) -> pa.RecordBatch:
        n = len(next(iter(columns.values())))
        fixed = {"shard": [shard] * n, "kind": [kind] * n, "part": [part] * n}
        types = (pa.int32(),) * 3 + (pa.binary(),) * 2 + (pa.int32(),) * 2 + (pa.float64(),) * 3
        names = ("shard", "kind", "part", "keys", "counts", "latest", "node", "n0", "n1", "below")
        return pa.RecordBatch.from_arrays([pa.array((fixed | columns).get(c, [None] * n), t) for c, t in zip(names, types, strict=True)], names)

    for k in range(0, len(keys), ROW_KEYS):
        yield rows(1, keys=[packed(keys[k : k + ROW_KEYS])], counts=[packed(counts[k : k + ROW_KEYS].astype(np.int64))])
    if not kind:
        yield rows(2, latest=[-1], node=[0], n0=[float(counts.sum())], n1=[float((counts > 0).sum())], below=[0.0])
    elif len(keys):
        trees = Subtrees(keys, counts)
        yield rows(0, keys=[np.stack([c.astype(float) for c in trees.middle]).tobytes()])
        latest, node, n0, n1, below = trees.summary()
        yield rows(2, latest=latest, node=node, n0=n0, n1=n1, below=below)


def merged_shards(sent: DataFrame, shards: int) -> DataFrame:
    """The sums of all blocks, one shard after the other; a task holds a shard's distinct keys."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, parts, size, least = None, [], 0, _MERGE_AT
        for batch in batches:
            for i in range(batch.num_rows):
                key = (batch.column("shard")[i].as_py(), batch.column("kind")[i].as_py())
                if key != now:
                    if parts:
                        yield from _merged_rows(*now, *_add_up(parts))
                    now, parts, size, least = key, [], 0, _MERGE_AT
                parts.append((unpacked(batch.column("keys")[i].as_py(), np.uint64), unpacked(batch.column("counts")[i].as_py(), np.uint32).astype(np.int64)))
                size += len(parts[-1][0])
                if size > least:
                    parts = [_add_up(parts)]
                    size = len(parts[0][0])
                    least = max(_MERGE_AT, 2 * size)
        if parts:
            yield from _merged_rows(*now, *_add_up(parts))

    return sent.select("shard", "kind", "keys", "counts").repartition(shards, "shard").sortWithinPartitions("shard", "kind").mapInArrow(work, _MERGED)


def _add_up(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    return summed(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))


def answers_to(sent: DataFrame, merged: DataFrame, top, shards: int) -> DataFrame:
    """For every row that was sent, what it asked: counts of words, or logarithms of the probabilities of bytes."""
    tables = merged.filter("part < 2").select(F.lit(None).cast("bigint").alias("block"), "shard", "kind", "part", "keys", "counts", F.lit(0).alias("at"))
    asked = sent.select("block", "shard", "kind", F.lit(3).alias("part"), "keys", F.lit(None).cast("binary").alias("counts"), "at")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, middle, parts, keys, values = None, None, [], None, None
        for batch in batches:
            for i in range(batch.num_rows):
                shard, kind, part, data = (batch.column(c)[i].as_py() for c in ("shard", "kind", "part", "keys"))
                if (shard, kind) != now:
                    now, middle, parts, keys, values = (shard, kind), None, [], None, None
                if part == 0:
                    middle = np.frombuffer(data, float).reshape(5, -1)
                    middle = [*middle[:2].astype(np.int64), *middle[2:]]
                elif part == 1:
                    parts.append((unpacked(data, np.uint64), unpacked(batch.column("counts")[i].as_py(), np.int64)))
                else:
                    if keys is None:
                        order = np.argsort([p[0][0] for p in parts])
                        keys, counts = (np.concatenate([parts[o][c] for o in order]) for c in (0, 1))
                        values = Subtrees(keys, counts, middle).log_chances(top.value) if kind else counts
                        parts = []
                    found = values[np.searchsorted(keys, unpacked(data, np.uint64))].astype(np.float32 if kind else np.int64)
                    yield pa.RecordBatch.from_pydict({"block": batch.column("block").slice(i, 1), "shard": pa.array([shard], pa.int32()), "kind": pa.array([kind], pa.int32()), "at": batch.column("at").slice(i, 1), "found": pa.array([packed(found)], pa.binary())})

    both = tables.unionByName(asked).repartition(shards, "shard").sortWithinPartitions("shard", "kind", "part")
    return both.mapInArrow(work, "block bigint, shard int, kind int, at int, found binary")


def score_texts(docs: DataFrame, training: Column) -> DataFrame:
    """doc_id, trained, n_tokens, n_known, train_tokens, base_score, score, n_bytes and bits_per_byte of every row."""
    spark = docs.sparkSession
    rows = with_blocks(docs, training)
    shards = max(shuffle_partitions(spark), len(docs.inputFiles()))
    sent = save(send_keys(rows, shards), "contexts")
    merged = save(merged_shards(sent, shards), "contexts")
    by_node = merged.filter("part = 2").groupBy("latest", "node").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("below").alias("below"))
    found = sorted(tuple(r) for r in by_node.collect())  # at most 256 * 255 + 1 rows
    texts = rows.filter("trained").count()
    words = [f for f in found if f[0] < 0]
    total = int(words[0][2] if words else 0) + texts
    distinct = int(words[0][3] if words else 0) + (texts > 0)
    top_rows = np.array([f for f in found if f[0] >= 0] or np.zeros((0, 5)), float)
    top = spark.sparkContext.broadcast(TopNodes(top_rows[:, 0].astype(int), top_rows[:, 1].astype(int), *top_rows[:, 2:].T))
    answers = answers_to(sent, merged, top, shards)
    per_token = np.log10(total + 0.5 * (distinct + 1))

    def score(left: pa.Table, right: pa.Table) -> pa.Table:
        n = left.num_rows
        out = {"doc_id": left["doc_id"], "trained": left["trained"], "n_tokens": np.zeros(n, np.int64), "n_known": np.zeros(n, np.int64), "base_score": np.zeros(n), "score": np.zeros(n), "n_bytes": np.zeros(n, np.int64)}
        if n:
            column = left["text"].combine_chunks()
            column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
            known = []
            for kind, (keys, _) in enumerate(block_keys(column, np.zeros(n, bool))):
                mine = right.filter(pc.equal(right["kind"], kind)).select(["shard", "at", "found"]).to_pylist()
                shard, values = shard_of(keys, kind, shards), np.zeros(len(keys))
                if len(keys):
                    got = [unpacked(r["found"], np.float32 if kind else np.int64) for r in sorted(mine, key=lambda r: (r["shard"], r["at"]))]
                    values[np.argsort(shard, kind="stable")] = np.concatenate(got)
                known.append((keys, values))
            end_score = np.log10(texts + 0.5) - per_token
            for first, end, data, off in slices(column):
                stream, symbol, start, spans = byte_stream(data, off)
                for kind, keys, row in ((0, word_hashes(data, spans[0], spans[1]) >> np.uint64(1), spans[2]), (1, context_keys(stream, symbol), np.repeat(np.arange(end - first), np.diff(start))[symbol])):
                    order = np.argsort(keys)
                    values = np.empty(len(keys))
                    values[order] = known[kind][1][np.searchsorted(known[kind][0], keys[order])]
                    size = end - first
                    if kind:
                        out["score"][first:end] = np.bincount(row, weights=values, minlength=size) / np.log(10)
                        out["n_bytes"][first:end] = np.bincount(row, minlength=size)
                    else:
                        out["n_tokens"][first:end] = np.bincount(row, minlength=size) + 1
                        out["n_known"][first:end] = np.bincount(row, weights=values > 0, minlength=size) + (texts > 0)
                        out["base_score"][first:end] = np.bincount(row, weights=np.log10(values + 0.5) - per_token, minlength=size) + end_score
        return pa.table(out)

    scored = rows.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(score, "doc_id bigint, trained boolean, n_tokens bigint, n_known bigint, base_score double, score double, n_bytes bigint")
    return scored.select("*", F.lit(total).cast("bigint").alias("train_tokens"), (-F.col("score") / F.col("n_bytes") * float(np.log2(10))).alias("bits_per_byte"))


def op3_context_tree_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows without doc_id are learnt from."""
    training = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 != 1, F.lit(True))
    scored = score_texts(documents(spark, sf_dir), training)
    return scored.select("doc_id", (~F.col("trained")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", "n_bytes", "bits_per_byte")
