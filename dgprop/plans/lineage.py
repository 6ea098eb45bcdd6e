"""Cutting lineage in the shared folder, and running iterations without re-planning."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder that the cluster names; set one of our own only where none is set."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None:
            named = tempfile.mkdtemp(prefix="dgprop-")
            atexit.register(shutil.rmtree, named, True)
        context.setCheckpointDir(named)


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint: survives lost executors and ends the lineage."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """Like ``cut``, but the rows are worked out only once (a checkpoint runs its last stage again); partitions are not kept."""
    ensure_checkpoint_dir(df.sparkSession)
    folder = f"{df.sparkSession.sparkContext.getCheckpointDir()}/stored-{uuid.uuid4().hex}"
    df.write.parquet(folder)
    return df.sparkSession.read.schema(df.schema).parquet(folder)


def at_once(f: Callable, of: list) -> list:
    """Of each value what ``f`` gives, with their Spark jobs side by side."""
    with ThreadPoolExecutor(max(1, len(of))) as pool:
        return list(pool.map(f, of))


@contextmanager
def fixed_plans(spark: SparkSession) -> Iterator[None]:
    """Without adaptive execution, checkpoints keep their partitioning and loops need one exchange a round."""
    old = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        yield
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", old)


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def count_exchanges(df: DataFrame) -> int:
    return len(re.findall(r"\bExchange (?:hash|range|single|round)", plan_text(df)))
