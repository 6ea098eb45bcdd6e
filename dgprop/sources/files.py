"""Edge lists from files and streams, and sinks for what is computed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dgprop.schemas import EVENTS, check

EDGE_LIST = "src bigint, dst bigint, w double, ts_us bigint"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE_LIST, **options: str) -> DataFrame:
    """Parquet, orc, csv or json with an explicit schema: nothing is inferred."""
    return spark.read.schema(schema).format(fmt).options(**options).load(path)


def read_edge_text(spark: SparkSession, path: str, separator: str = " ") -> DataFrame:
    """Lines ``src dst [w [ts_us]]``; lines that start with # are comments, those without two ids are left out."""
    part = F.split(F.trim("value"), separator)
    lines = spark.read.text(path).filter(~F.trim("value").startswith("#"))
    number = lambda i, kind: F.get(part, F.lit(i)).try_cast(kind)
    rows = lines.select(number(0, "bigint").alias("src"), number(1, "bigint").alias("dst"), F.coalesce(number(2, "double"), F.lit(1.0)).alias("w"), number(3, "bigint").alias("ts_us"))
    return rows.filter("src IS NOT NULL AND dst IS NOT NULL")


def stream_events(spark: SparkSession, folder: str) -> DataFrame:
    """New parquet files of events in a folder, as a stream."""
    return spark.readStream.schema(EVENTS).parquet(folder)


def normalise(df: DataFrame, ts_us: str, src: str, dst: str, kind: str | None = None, w: str | None = None) -> DataFrame:
    """Any table as events: expressions for the columns, a hash of the row as seq."""
    return df.select(
        F.xxhash64(*[F.col(c).cast("string") for c in df.columns]).alias("seq"),
        F.expr(ts_us).cast("bigint").alias("ts_us"),
        (F.expr(kind) if kind else F.lit("add_edge")).alias("kind"),
        F.expr(src).cast("bigint").alias("src"),
        F.expr(dst).cast("bigint").alias("dst"),
        (F.expr(w) if w else F.lit(1.0)).cast("double").alias("w"),
    )


def write_steps(df: DataFrame, path: str) -> None:
    """Rows with a step, in one folder for each step; a step that is written again replaces its folder only."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("step").parquet(path)


def read_steps(spark: SparkSession, path: str, low: int, high: int) -> DataFrame:
    """The steps from ``low`` to ``high``; the other folders aren't read."""
    return spark.read.parquet(path).filter(F.col("step").between(low, high))


def write_bucketed(edges: DataFrame, table: str, buckets: int) -> None:
    """A table of edges bucketed and sorted by source: joins on the source need no exchange."""
    check(edges, "src bigint, dst bigint, w double").write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").format("parquet").saveAsTable(table)


def export(df: DataFrame, path: str, fmt: str = "json") -> None:
    """Small results, as csv with a header or as json."""
    df.write.mode("overwrite").format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(path)
