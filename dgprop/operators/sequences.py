"""From representations by step to sequences of changes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dgprop.functions.vectors import cosine, vec_norm, vec_sub


def with_earlier(representations: DataFrame) -> DataFrame:
    """step and node of the rows that ``deltas`` has, without their vectors."""
    past = Window.partitionBy("node").orderBy("step")
    there = representations.select("step", "node", F.col("z").isNotNull().alias("there"))
    return there.withColumn("old", F.lag("there").over(past)).filter("old").select("step", "node")


def with_asked(representations: DataFrame, asked: DataFrame) -> DataFrame:
    """Add ``asked``: whether the row's step and node are among the asked ones.

    By a union and in the order of steps, so that changes and sequences of the rows move them no more.
    """
    order = Window.partitionBy("node").orderBy("step", "own")
    rows = representations.select("step", "node", "z", F.lit(1).alias("own"))
    marks = asked.select("step", "node", F.lit(None).cast(rows.schema["z"].dataType).alias("z"), F.lit(0).alias("own"))
    here = (F.lag("own").over(order) == 0) & (F.lag("step").over(order) == F.col("step"))
    return rows.unionByName(marks).withColumn("asked", F.coalesce(here, F.lit(False))).filter("own = 1").drop("own")


def deltas(representations: DataFrame, kind: str = "diff", *more: str) -> DataFrame:
    """step, node, delta: the change from the node's row before; its first row has none. ``more`` names columns that stay.

    ``diff`` is the difference, ``l2`` its length, ``cosine`` one less the cosine, each as an array.
    """
    past = Window.partitionBy("node").orderBy("step")
    both = representations.withColumn("old", F.lag("z").over(past)).filter("old IS NOT NULL")
    change = {
        "diff": vec_sub(F.col("z"), F.col("old")),
        "l2": F.array(vec_norm(vec_sub(F.col("z"), F.col("old")))),
        "cosine": F.array(1 - F.coalesce(cosine(F.col("z"), F.col("old")), F.lit(0.0))),
    }
    return both.select("step", "node", *more, (kind(F.col("z"), F.col("old")) if callable(kind) else change[kind]).alias("delta"))


def sequences(changes: DataFrame, length: int, *more: str) -> DataFrame:
    """step, node and the last ``length`` changes up to the step, oldest first."""
    window = Window.partitionBy("node").orderBy("step").rowsBetween(-(length - 1), 0)
    return changes.select("step", "node", *more, F.collect_list("delta").over(window).alias("deltas"))


def influence(changes: DataFrame, top: int) -> DataFrame:
    """For each step and place the nodes with the greatest change: step, dim, rank, node, score."""
    each = changes.select("step", "node", F.posexplode("delta").alias("dim", "v"))
    ranked = each.withColumn("rank", F.row_number().over(Window.partitionBy("step", "dim").orderBy(F.desc(F.round(F.abs("v"), 9)), "node")))
    return ranked.filter(F.col("rank") <= top).select("step", "dim", "rank", "node", F.abs("v").alias("score"))


def as_of(representations: DataFrame, queries: DataFrame) -> DataFrame:
    """Each query (node, step) with the node's latest row at or before the step; linear in rows, by a union."""
    rows = representations.select("node", "step", F.lit(0).alias("late"), F.struct(F.col("step").alias("at"), "z").alias("r"), F.lit(None).cast("bigint").alias("query_id"))
    asked = queries.select("node", "step", F.lit(1).alias("late"), F.lit(None).cast(rows.schema["r"].dataType).alias("r"), "query_id")
    order = Window.partitionBy("node").orderBy("step", "late").rowsBetween(Window.unboundedPreceding, 0)
    found = rows.unionByName(asked).withColumn("r", F.last("r", ignorenulls=True).over(order))
    return found.filter("late = 1 AND r IS NOT NULL").select("query_id", "node", "step", F.col("r.at").alias("as_of"), F.col("r.z").alias("z"))
