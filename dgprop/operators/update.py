"""Repair of the push state after changes of the graph or the features.

The estimates stay; only the residuals of the nodes at changed edges, and of nodes
with new features, are worked out anew, and pushing goes on from there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dgprop.operators.filters import FilterSpec
from dgprop.operators.propagate import cells


def repair(state: DataFrame, deltas: DataFrame, edges_before: DataFrame, features: DataFrame, specs: list[FilterSpec], dim: int, new_features: DataFrame | None = None) -> DataFrame:
    """State for the graph after ``deltas``; nodes of the features that are new come in with estimate 0.

    ``deltas`` holds both directions of every change.  Only touched nodes get a new
    residual; the join with the adjacency is limited to their degrees.
    """
    ys = cells("y", specs, dim)
    blank = [F.lit(0.0).alias(c) for c in ys]
    known = state.select("node")
    now = features if new_features is None else features.join(new_features.select("node"), "node", "left_anti").unionByName(new_features)
    fresh = now.join(known, "node", "left_anti").select("node", F.lit(1.0).alias("D"), *blank, *[F.col("x")[i].alias(f"q{s}_{i}") for s in range(len(specs)) for i in range(dim)])
    all_nodes = state.unionByName(fresh)
    moved = deltas.groupBy(F.col("src").alias("node")).agg(F.sum("dw").alias("dD"))
    changed = moved.select("node") if new_features is None else moved.select("node").union(new_features.select("node")).distinct()
    touched_edges = edges_before.join(changed.select(F.col("node").alias("src")), "src", "left_semi")
    d_old = touched_edges.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("d_old"))
    pull = deltas.join(all_nodes.select(F.col("node").alias("dst"), *ys), "dst").groupBy(F.col("src").alias("node")).agg(*[F.sum(F.col("dw") * F.col(y)).alias("m" + y[1:]) for y in ys])
    old_x = features.select("node", F.col("x").alias("x0"))
    t = all_nodes.join(changed.withColumn("_hit", F.lit(True)), "node", "left").join(moved, "node", "left").join(d_old, "node", "left").join(pull, "node", "left").join(old_x, "node", "left").join(now.select("node", F.col("x").alias("x1")), "node", "left")
    zero = F.lit(0.0)
    d_new = F.coalesce("d_old", zero) + F.coalesce("dD", zero)
    new_d = F.when(F.col("_hit"), F.when(d_new > 1e-12, d_new).otherwise(F.lit(1.0))).otherwise(F.col("D"))
    t = t.withColumn("D_new", new_d)
    out = []
    for s, spec in enumerate(specs):
        for i in range(dim):
            y, q = F.col(f"y{s}_{i}"), F.col(f"q{s}_{i}")
            x0, x1 = F.coalesce(F.col("x0")[i], F.col("x1")[i]), F.col("x1")[i]
            # What the old neighbours add up to, times ratio / D_old, follows from the old residual.
            held = (y + spec.g0 * q - spec.g0 * x0 * F.pow("D", F.lit(spec.beta - 1))) * F.col("D")
            right = spec.g0 * x1 * F.pow("D_new", F.lit(spec.beta - 1)) + (held + spec.ratio * F.coalesce(F.col(f"m{s}_{i}"), zero)) / F.col("D_new")
            out.append(F.when(F.col("_hit"), (right - y) / spec.g0).otherwise(q).alias(f"q{s}_{i}"))
    return t.select("node", F.col("D_new").alias("D"), *ys, *out)


def repair_pull(state: DataFrame, edges_after: DataFrame, touched: DataFrame, features: DataFrame, specs: list[FilterSpec], dim: int) -> DataFrame:
    """The same from the touched nodes' present neighbours; it also takes away rounding that has built up."""
    ys = cells("y", specs, dim)
    mine = edges_after.join(touched.select(F.col("node").alias("src")), "src", "left_semi")
    d = mine.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("d_now"))
    sums = mine.join(state.select(F.col("node").alias("dst"), *ys), "dst").groupBy(F.col("src").alias("node")).agg(*[F.sum(F.col("w") * F.col(y)).alias("n" + y[1:]) for y in ys])
    t = state.join(touched.select("node", F.lit(True).alias("_hit")).distinct(), "node", "left").join(d, "node", "left").join(sums, "node", "left").join(features, "node")
    new_d = F.when(F.col("_hit"), F.coalesce(F.when(F.col("d_now") > 1e-12, F.col("d_now")), F.lit(1.0))).otherwise(F.col("D"))
    t = t.withColumn("D_new", new_d)
    out = []
    for s, spec in enumerate(specs):
        for i in range(dim):
            right = spec.g0 * F.col("x")[i] * F.pow("D_new", F.lit(spec.beta - 1)) + spec.ratio / F.col("D_new") * F.coalesce(F.col(f"n{s}_{i}"), F.lit(0.0))
            out.append(F.when(F.col("_hit"), (right - F.col(f"y{s}_{i}")) / spec.g0).otherwise(F.col(f"q{s}_{i}")).alias(f"q{s}_{i}"))
    return t.select("node", F.col("D_new").alias("D"), *ys, *out)


def drop_nodes(state: DataFrame, gone: DataFrame) -> DataFrame:
    """Take out nodes whose edges are gone already."""
    return state.join(gone, "node", "left_anti")
