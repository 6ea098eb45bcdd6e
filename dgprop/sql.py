"""Views and functions by which the graph can be asked in SQL text."""

from __future__ import annotations

from pyspark.sql import SparkSession

from dgprop.functions.udfs import half_edges, squash
from dgprop.operators import graph as G
from dgprop.sources import tables as T


def register(spark: SparkSession, sf_dir: str) -> None:
    """Views dg_events, dg_edges, dg_degrees, dg_deltas; functions dg_squash and dg_half_edges."""
    events = T.interactions(spark, sf_dir)
    edges = G.weighted(G.mirrored(events.select("src", "dst", "w")))
    for name, df in {"dg_events": events, "dg_edges": edges, "dg_degrees": G.degrees(edges), "dg_deltas": G.net_deltas(events.withColumn("step", G.bucket()))}.items():
        df.createOrReplaceTempView(name)
    spark.udf.register("dg_squash", squash)
    spark.udtf.register("dg_half_edges", half_edges)
