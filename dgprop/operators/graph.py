"""Edges, degrees, snapshots and their differences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dgprop.sources.tables import DAY_US

TINY = 1e-12


def mirrored(edges: DataFrame, weight: str = "w") -> DataFrame:
    """Both directions of every edge; self-loops once."""
    others = [c for c in edges.columns if c not in ("src", "dst")]
    back = edges.filter("src <> dst").select(F.col("dst").alias("src"), F.col("src").alias("dst"), *others)
    return edges.select("src", "dst", *others).unionByName(back)


def weighted(events: DataFrame) -> DataFrame:
    """Repeated edges are one edge whose weight is their sum."""
    return events.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def signed(events: DataFrame) -> DataFrame:
    """Edge events with their signed weight dw; other kinds are left out."""
    sign = F.when(F.col("kind") == "add_edge", 1).when(F.col("kind") == "del_edge", -1)
    return events.filter(F.col("kind").isin("add_edge", "del_edge")).withColumn("dw", sign * F.coalesce(F.col("w"), F.lit(1.0)))


def bucket(width_us: int = DAY_US, origin_us: int = 0) -> Column:
    """The step of a timestamp: the number of whole widths since the origin."""
    return F.floor((F.col("ts_us") - origin_us) / width_us).cast("int")


def month() -> Column:
    """The step of a timestamp: months since the year 0."""
    at = F.timestamp_micros("ts_us")
    return (F.year(at) * 12 + F.month(at) - 1).cast("int")


def by_timestamp(events: DataFrame) -> DataFrame:
    """One step for each distinct time, numbered from 0: the numbering is of the (small) table of times in ranges."""
    times = events.select("ts_us").distinct()
    days = times.groupBy(F.floor(F.col("ts_us") / DAY_US).alias("day")).count()
    from pyspark.sql import Window

    before = days.select("day", F.coalesce(F.sum("count").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.row_number().over(Window.partitionBy("day").orderBy("ts_us")) - 1
    steps = times.withColumn("day", F.floor(F.col("ts_us") / DAY_US)).withColumn("inside", inside).join(F.broadcast(before), "day")
    return events.join(steps.select("ts_us", (F.col("before") + F.col("inside")).cast("int").alias("step")), "ts_us")


def by_count(events: DataFrame, width: int) -> DataFrame:
    """Steps of ``width`` events in the order of time, then seq."""
    from pyspark.sql import Window

    day = F.floor(F.col("ts_us") / DAY_US)
    days = events.groupBy(day.alias("day")).count()
    before = days.select("day", F.coalesce(F.sum("count").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.row_number().over(Window.partitionBy("day").orderBy("ts_us", "seq", "kind")) - 1
    placed = events.withColumn("day", day).withColumn("inside", inside).join(F.broadcast(before), "day")
    return placed.withColumn("step", F.floor((F.col("before") + F.col("inside")) / width).cast("int")).drop("day", "inside", "before")


def net_deltas(stepped: DataFrame, undirected: bool = True) -> DataFrame:
    """step, src, dst, dw: simultaneous events summed up, those that cancel left out."""
    events = signed(stepped).select("step", "src", "dst", "dw")
    both = mirrored(events) if undirected else events
    return both.groupBy("step", "src", "dst").agg(F.sum("dw").alias("dw")).filter(F.abs("dw") > TINY)


def clamp_deltas(deltas: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Deltas that never take a weight below zero, and the part of each that was refused.

    With running sum S of what is asked for, the weight is S less the least of 0 and all S so far.
    """
    from pyspark.sql import Window

    past = Window.partitionBy("src", "dst").orderBy("step")
    up_to = past.rowsBetween(Window.unboundedPreceding, 0)
    run = deltas.withColumn("_sum", F.sum("dw").over(up_to))
    run = run.withColumn("_low", F.least(F.lit(0.0), F.min("_sum").over(up_to)))
    run = run.withColumn("_w", F.col("_sum") - F.col("_low")).withColumn("_before", F.coalesce(F.lag("_w").over(past), F.lit(0.0)))
    real = run.withColumn("_real", F.col("_w") - F.col("_before"))
    kept = real.filter(F.abs("_real") > TINY).select("step", "src", "dst", F.col("_real").alias("dw"))
    refused = real.filter(F.abs(F.col("dw") - F.col("_real")) > TINY).select("step", "src", "dst", (F.col("dw") - F.col("_real")).alias("dw"))
    return kept, refused


def graph_at(deltas: DataFrame, step: int) -> DataFrame:
    """The edges after all deltas up to ``step``."""
    return deltas.filter(F.col("step") <= step).groupBy("src", "dst").agg(F.sum("dw").alias("w")).filter(F.col("w") > TINY)


def apply_deltas(edges: DataFrame, deltas: DataFrame) -> DataFrame:
    both = edges.select("src", "dst", "w").unionByName(deltas.select("src", "dst", F.col("dw").alias("w")))
    return both.groupBy("src", "dst").agg(F.sum("w").alias("w")).filter(F.col("w") > TINY)


def snapshot_diff(before: DataFrame, after: DataFrame) -> DataFrame:
    """src, dst, dw that turn one snapshot into the other."""
    both = after.select("src", "dst", F.col("w").alias("dw")).unionByName(before.select("src", "dst", (-F.col("w")).alias("dw")))
    return both.groupBy("src", "dst").agg(F.sum("dw").alias("dw")).filter(F.abs("dw") > TINY)


def snapshots(deltas: DataFrame, steps: list[int]) -> DataFrame:
    """The graph at each of the steps: step, src, dst, w.

    Deltas are summed up to the first step at or after them, then carried on.
    """
    at = F.array(*[F.lit(s) for s in sorted(steps)])
    first = F.filter(at, lambda s: s >= F.col("step"))
    known = deltas.withColumn("_steps", first).filter(F.size("_steps") > 0).select(F.explode("_steps").alias("step"), "src", "dst", "dw")
    return known.groupBy("step", "src", "dst").agg(F.sum("dw").alias("w")).filter(F.col("w") > TINY)


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("d"))


def update_degrees(old: DataFrame, deltas: DataFrame) -> DataFrame:
    both = old.unionByName(deltas.select(F.col("src").alias("node"), F.col("dw").alias("d")))
    return both.groupBy("node").agg(F.sum("d").alias("d"))


def affected(deltas: DataFrame, changed_features: DataFrame | None = None) -> DataFrame:
    """Ends of changed edges, and nodes with changed features."""
    ends = deltas.select(F.col("src").alias("node")).union(deltas.select(F.col("dst").alias("node")))
    if changed_features is not None:
        ends = ends.union(changed_features.select("node"))
    return ends.distinct()


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("node")).union(edges.select(F.col("dst").alias("node"))).distinct()


def delete_node_deltas(edges: DataFrame, gone: DataFrame) -> DataFrame:
    """The deltas that take away all edges of the given nodes."""
    out = edges.join(gone.select(F.col("node").alias("src")), "src", "left_semi")
    into = edges.join(gone.select(F.col("node").alias("dst")), "dst", "left_semi").select(*edges.columns)
    return out.select(*edges.columns).union(into).distinct().select("src", "dst", (-F.col("w")).alias("dw"))


def graph_stats(deltas: DataFrame) -> DataFrame:
    """Nodes, temporal edges, distinct edges and steps of a table of directed edge events with a step."""
    ends = deltas.select(F.explode(F.array("src", "dst")).alias("node"))
    n = ends.agg(F.countDistinct("node").alias("n_nodes"))
    rest = deltas.agg(F.count("*").alias("n_temporal_edges"), F.countDistinct("src", "dst").alias("n_edges"), F.countDistinct("step").alias("n_steps"))
    return n.join(rest)
