"""Splits of pairs in time, and of nodes by hash."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dgprop.functions.hashing import hash32


def time_split(pairs: DataFrame, train: int = 70, valid: int = 15) -> DataFrame:
    """Add ``part``: train, valid or test by the percent of pairs before the step; ties stay together.

    Only the table of steps is summed up in order, not the pairs.
    """
    before = F.coalesce(F.sum("n").over(Window.orderBy("step").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    steps = pairs.groupBy("step").agg(F.count("*").alias("n")).withColumn("before", before)
    total = pairs.agg(F.count("*").alias("total"))
    share = F.col("before") * 100
    part = F.when(share < F.col("total") * train, "train").when(share < F.col("total") * (train + valid), "valid").otherwise("test")
    return pairs.join(F.broadcast(steps.join(total).select("step", part.alias("part"))), "step")


def holdout_nodes(nodes: DataFrame, percent: int, seed: int) -> DataFrame:
    return nodes.filter(F.pmod(hash32(seed, F.col("node")), F.lit(100)) < percent)


def in_setting(pairs: DataFrame, setting: str) -> DataFrame:
    """Test pairs whose ends are both among the training pairs' (transductive), or not (inductive)."""
    train = pairs.filter("part = 'train'")
    test = pairs.filter("part = 'test'")
    src, dst = train.select("src").distinct(), train.select("dst").distinct()
    seen = test.join(src, "src", "left_semi").join(dst, "dst", "left_semi")
    if setting == "transductive":
        return seen.select(*pairs.columns)
    unseen = test.join(src, "src", "left_anti").select(*pairs.columns).union(test.join(src, "src", "left_semi").join(dst, "dst", "left_anti").select(*pairs.columns))
    return unseen


def negatives(pairs: DataFrame, pool: DataFrame, k: int, seed: int, known: DataFrame | None = None) -> DataFrame:
    """For each pair ``k`` others with the same source and a target of the pool that the source is not known to be linked with.

    ``pool`` has idx (0 to N - 1) and node.  A hash draws a number below the count of
    the source's free targets, and that many known ones before it move it on, so
    every draw is one of them.  A source with at most ``k`` free targets gets each of
    them once (``n_free`` says how many there are), one without any gets none.
    """
    n = pool.agg(F.count("*").alias("n_pool"))
    linked = (pairs if known is None else known).select("src", "dst").distinct().join(pool.select("idx", F.col("node").alias("dst")), "dst")
    # Of the i-th known place, the free places before it.
    taken = linked.groupBy("src").agg(F.transform(F.array_sort(F.collect_list("idx")), lambda x, i: x - i).alias("taken"))
    drawn = pairs.select("query_id", "step", "src").join(taken, "src", "left").crossJoin(F.broadcast(n))
    drawn = drawn.withColumn("taken", F.coalesce("taken", F.array().cast("array<bigint>"))).withColumn("n_free", F.col("n_pool") - F.size("taken")).filter("n_free > 0")
    places = F.when(F.col("n_free") <= k, F.sequence(F.lit(0).cast("bigint"), F.col("n_free") - 1)).otherwise(
        F.transform(F.sequence(F.lit(1), F.lit(max(k, 1))), lambda j: F.pmod(hash32(seed, F.col("query_id"), j), F.col("n_free")).cast("bigint"))
    )
    drawn = drawn.select("query_id", "step", "src", "n_free", "taken", places.alias("places")).filter(F.lit(k > 0))
    kept = "query_id", "step", "src", "n_free"

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            taken, places = batch.column("taken"), batch.column("places")
            known, wanted = taken.flatten().to_numpy(zero_copy_only=False), places.flatten().to_numpy(zero_copy_only=False)
            row = lambda lists: np.repeat(np.arange(batch.num_rows), lists.value_lengths().to_numpy())
            # Of all rows at once: numbers of one row are apart from those of the next.
            span = int(max(known.max(initial=0), wanted.max(initial=0))) + 1
            ahead = np.searchsorted(known + row(taken) * span, wanted + row(places) * span, side="right")
            before = np.concatenate(([0], np.cumsum(taken.value_lengths().to_numpy())))[:-1]
            idx = wanted + ahead - before[row(places)]
            offsets = np.concatenate(([0], np.cumsum(places.value_lengths().to_numpy()))).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.ListArray.from_arrays(offsets, idx)], [*kept, "idx"])

    types = dict(pairs.dtypes)
    placed = drawn.mapInArrow(work, f"query_id {types['query_id']}, step {types['step']}, src {types['src']}, n_free bigint, idx array<bigint>")
    each = placed.select(*kept, F.posexplode("idx").alias("j", "idx")).withColumn("j", F.col("j") + 1)
    return each.join(pool.select("idx", F.col("node").alias("dst")), "idx").select("query_id", "step", "src", "dst", F.lit(0).alias("label"), "j", "n_free")


def indexed(nodes: DataFrame) -> DataFrame:
    """idx from 0 in the order of node, for pools of nodes of one kind: ranges first, then places inside."""
    ranges = nodes.select("node", F.floor(F.col("node") / 1000).alias("r"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ahead = ranges.groupBy("r").agg(F.count("*").alias("n")).select("r", before.alias("ahead"))
    inside = F.row_number().over(Window.partitionBy("r").orderBy("node")) - 1
    return ranges.withColumn("inside", inside).join(ahead, "r").select((F.col("ahead") + F.col("inside")).alias("idx"), "node")
