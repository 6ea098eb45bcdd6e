"""Connected components of an edge table, by minima along edges.

Rounds of two steps: every node hands its least neighbour to its greater
neighbours, then every node hands the least of its lesser neighbours to the others
and itself.  Edges end as stars around the least node of each component after a
number of rounds that grows with the logarithm of the nodes.  Both steps are
aggregations to minima and joins that can be split, so a node with very many
neighbours is no hot key.  Each round is a table in the shared folder.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dgprop.llm.common import save


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).head())


def _greater(edges: DataFrame) -> DataFrame:
    """Edges (a, b) with a > b, after each node joined its greater neighbours to its least one."""
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()


def _lesser(edges: DataFrame) -> DataFrame:
    """Edges (a, b) with a > b, after each node joined itself and its lesser neighbours to the least one."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    joined = edges.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b")
    return joined.union(least.select("a", F.col("m").alias("b"))).distinct()


def components(edges: DataFrame, save: Callable[[DataFrame, str], DataFrame] = save) -> DataFrame:
    """From undirected edges (a, b): node and root, the least node it is connected with; nodes without edges are not in it."""
    now = save(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = _state(now)
    while state[0]:
        now = save(_lesser(_greater(now)), "edges")
        new = _state(now)
        if new == state:
            break
        state = new
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
