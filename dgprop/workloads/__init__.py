"""Queries on the given tables, and the flagship."""

from __future__ import annotations

from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

from dgprop.workloads.registry import QUERIES, SQL

MODULES = ("graphs", "updates", "relational", "streams", "learning", "baselines")


def load() -> tuple[dict, dict]:
    """All queries and their SQL."""
    for name in MODULES:
        import_module(f"dgprop.workloads.{name}")
    return QUERIES, SQL


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Representations of every daily step of users and items in both bands, repaired from day to day."""
    from dgprop.operators.filters import FilterSpec
    from dgprop.operators.timeline import run_timeline
    from dgprop.workloads.graphs import daily, random_x

    deltas = daily(spark, sf_dir)
    specs = [FilterSpec.restart(0.2), FilterSpec.alternating(0.2)]
    return run_timeline(deltas, random_x(deltas.withColumnRenamed("dw", "w"), 8), specs, 1e-4, 8).representations
