"""Toxicity by a linear classifier on character n-grams scaled by naive Bayes ratios.

A text's features are its distinct n-grams of characters (code points, A to Z
lower-cased), hashed to ``2 ** BITS`` cells.  From labelled texts each cell gets
the logarithm of the ratio of its shares among toxic and other texts, smoothed in
proportion to the classes; a logistic regression then weighs the cells, each
scaled by its ratio.  Scoring adds up one number for each distinct cell.

The classifier is fitted on labelled rows of at most ``MOST_ROWS`` ids and
``MOST_BYTES`` of text, those of the least hash; everything that is collected is
bounded by that and by the number of cells.  A cell with a ratio of less than
``LEAST_RATIO``, or in fewer than ``LEAST_TEXTS`` of these texts, has no weight.
Scoring covers all rows and whole texts, a very long one by itself.  Null and empty
texts have the score of no feature; a doc_id that is labelled more than once is
toxic if one of its labels says so; repeated rows and rows without doc_id are
scored each for itself, and all rows of a labelled id are learnt from; equal
hashes are ordered by doc_id; other columns are ignored; an empty table gives an
empty result; without both classes the score is the share of toxic labels.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.llm.common import documents
from dgprop.llm.textblocks import LOWER, _BYTE_CODES, _power_tables, mix, slices

BITS = 20
ORDERS = (3, 4, 5, 6)
#: Labelled rows that the classifier is fitted on, at most.
MOST_ROWS = 12_000
#: Bytes of their texts, at most.
MOST_BYTES = 64 << 20
#: Cells with a smaller ratio, or in fewer labelled texts, get no weight.
LEAST_RATIO, LEAST_TEXTS = 1.0, 10
#: Texts that smoothing adds, split between the classes as the labels are.
SMOOTH = 50.0


def cells_of(column: pa.Array, bits: int = BITS, orders: tuple[int, ...] = ORDERS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first row, end row, row of each cell, cell): the distinct cells of each row."""
    shift = np.uint64(64 - bits)
    for first, end, data, off in slices(column):
        n = len(data)
        sums = np.zeros(n + 1, np.uint64)
        up, down = _power_tables(n + 1)
        found = []
        with np.errstate(over="ignore"):
            np.cumsum(_BYTE_CODES[LOWER[data]] * up[:n], out=sums[1:])
            at = np.append(np.flatnonzero((data & 0xC0) != 0x80), n)  # where characters start
            row = np.searchsorted(off, at[:-1], "right") - 1
            for k in orders:
                if len(at) > k:
                    a, b = at[:-k], at[k:]
                    h = mix((sums[b] - sums[a]) * down[a] + (b - a).astype(np.uint64))
                    of = row[: len(a)]
                    inside = of == row[k - 1 :]
                    found.append((of << bits | (h >> shift).astype(np.int64))[inside])
        keys = np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64)
        if len(keys):
            keys = keys[np.concatenate(([True], keys[1:] != keys[:-1]))]
        yield first, end, keys >> bits, keys & ((1 << bits) - 1)


@dataclass(frozen=True)
class ToxicityModel:
    """A number for each cell, and one for all texts."""

    weights: np.ndarray
    bias: float

    def scores(self, column: pa.Array) -> np.ndarray:
        out = np.full(len(column), self.bias)
        bits = len(self.weights).bit_length() - 1
        for first, end, row, cell in cells_of(column, bits):
            out[first:end] += np.bincount(row, weights=self.weights[cell], minlength=end - first)
        return 1 / (1 + np.exp(-np.clip(out, -30, 30)))


def training_rows(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS, most_bytes: int = MOST_BYTES) -> DataFrame:
    """text and toxic of the labelled documents that are not held out, as many as the limits allow, in the order of a hash."""
    learn = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    learn = learn.filter(F.crc32(F.col("doc_id").cast("string")) % 5 != 0).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows)
    # As many ids as the limit says, so the broadcast and what is collected are bounded.
    learn = F.broadcast(learn.withColumn("order", F.xxhash64("doc_id")))
    sizes = docs.select("doc_id", F.octet_length("text").alias("size")).join(learn, "doc_id").groupBy("order", "doc_id").agg(F.sum("size").alias("size")).collect()
    room, keep = most_bytes, []
    for r in sorted(sizes, key=lambda r: (r["order"], r["doc_id"])):
        room -= r["size"] or 0
        if room < 0:
            break
        keep.append((r["doc_id"],))
    kept = docs.sparkSession.createDataFrame(keep, "doc_id bigint")
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(learn.join(kept, "doc_id", "left_semi")), "doc_id").select("text", F.col("toxic").cast("int").alias("toxic"))


def fit(rows: DataFrame, bits: int = BITS, rounds: int = 150, step: float = 0.02, penalty: float = 3e-4) -> ToxicityModel:
    """Fit on (text, toxic)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, n = np.zeros((2, 1 << bits), np.int32), [0, 0]
        for batch in batches:
            toxic = batch.column("toxic").to_numpy()
            for side in (0, 1):
                n[side] += int((toxic == side).sum())
            for first, end, row, cell in cells_of(batch.column("text"), bits):
                for side in (0, 1):
                    counts[side] += np.bincount(cell[toxic[first:end][row] == side], minlength=1 << bits).astype(np.int32)
        if sum(n):
            for side in (0, 1):
                for b in range(0, 1 << bits, 1 << 14):
                    yield pa.RecordBatch.from_pydict({"side": pa.array([side], pa.int32()), "block": pa.array([b], pa.int32()), "n": pa.array([n[side] if b == 0 else 0], pa.int64()), "cells": pa.array([counts[side, b : b + (1 << 14)].tobytes()], pa.binary())})

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}
        for batch in batches:
            for r in batch.to_pylist():
                kept = held.setdefault((r["side"], r["block"]), [0, np.zeros(1 << 14, np.int64)])
                kept[0] += r["n"]
                kept[1] = kept[1] + np.frombuffer(r["cells"], np.int32)
        for (side, b), (n, cells) in held.items():
            yield pa.RecordBatch.from_pydict({"side": pa.array([side], pa.int32()), "block": pa.array([b], pa.int32()), "n": pa.array([n], pa.int64()), "cells": pa.array([cells.tobytes()], pa.binary())})

    schema = "side int, block int, n bigint, cells binary"
    counts, texts = np.zeros((2, 1 << bits)), [0, 0]
    for r in rows.mapInArrow(count, schema).repartition(16, "side", "block").mapInArrow(total, schema).collect():  # of fixed size
        counts[r["side"], r["block"] : r["block"] + (1 << 14)] = np.frombuffer(r["cells"], np.int64)
        texts[r["side"]] += r["n"]
    share = (texts[1] + 0.5) / (sum(texts) + 1)
    if min(texts) == 0:
        return ToxicityModel(np.zeros(1 << bits), float(np.log(share / (1 - share))))
    smooth = [SMOOTH * t / sum(texts) for t in texts]
    ratio = np.log((counts[1] + smooth[1]) / (texts[1] + smooth[1])) - np.log((counts[0] + smooth[0]) / (texts[0] + smooth[0]))
    ratio[(np.abs(ratio) < LEAST_RATIO) | (counts.sum(0) < LEAST_TEXTS)] = 0
    used = ratio != 0

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, end, row, cell in cells_of(batch.column("text"), bits):
                keep = used[cell]
                bounds = np.searchsorted(row[keep], np.arange(end - first + 1))
                kept = cell[keep].astype(np.uint32)
                yield pa.RecordBatch.from_arrays([batch.column("toxic").slice(first, end - first), pa.array([kept[a:b].tobytes() for a, b in zip(bounds[:-1], bounds[1:], strict=True)], pa.binary())], ["toxic", "cells"])

    # Bounded by the rows that are fitted on; sorted, so that the fit does not depend on their order.
    held = sorted(((bytes(r["cells"]), r["toxic"]) for r in rows.mapInArrow(gather, "toxic int, cells binary").collect()))
    cells = np.frombuffer(b"".join(c for c, _ in held), np.uint32).astype(np.int64)
    sizes = np.array([len(c) // 4 for c, _ in held])
    row, y = np.repeat(np.arange(len(held)), sizes), np.array([t for _, t in held], float)
    kinds, place = np.unique(cells, return_inverse=True)
    scale = ratio[kinds]
    x = scale[place]
    w, b = np.zeros(len(kinds)), float(np.log(share / (1 - share)))
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for t in range(1, rounds + 1):
        margin = np.bincount(row, weights=x * w[place], minlength=len(held)) + b
        error = (1 / (1 + np.exp(-np.clip(margin, -30, 30))) - y) / len(held)
        g, gb = np.bincount(place, weights=x * error[row], minlength=len(kinds)) + penalty * w, float(error.sum())
        m, v, mb, vb = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g, 0.9 * mb + 0.1 * gb, 0.999 * vb + 0.001 * gb * gb
        c1, c2 = 1 - 0.9**t, 1 - 0.999**t
        w = w - step * (m / c1) / (np.sqrt(v / c2) + 1e-9)
        b -= step * (mb / c1) / (np.sqrt(vb / c2) + 1e-9)
    weights = np.zeros(1 << bits)
    weights[kinds] = w * scale
    return ToxicityModel(weights, b)


def score_toxicity(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, held_out, score and predicted of every row."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(held.value.scores(batch.column("text")))], ["doc_id", "score"])

    scored = docs.select("doc_id", "text").mapInArrow(work, "doc_id bigint, score double")
    return scored.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = fit(training_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return score_toxicity(docs, model)
