"""Accuracy measures on tables of scores."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _score_groups(df: DataFrame, by: list[str]) -> DataFrame:
    """Positives and rows at every distinct score: ties count together, and the window is over these groups."""
    return df.groupBy(*by, "score").agg(F.sum("label").cast("double").alias("pos"), F.count("*").cast("double").alias("n"))


def average_precision(df: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Sum over falling scores of the gain in recall times the precision."""
    by = by or []
    down = Window.partitionBy(*by).orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    run = _score_groups(df, by).withColumns({"tp": F.sum("pos").over(down), "seen": F.sum("n").over(down)})
    return run.groupBy(*by).agg(F.try_divide(F.sum(F.col("pos") * F.col("tp") / F.col("seen")), F.sum("pos")).alias("average_precision"))


def roc_auc(df: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The share of pairs of a positive and a negative that are in order, ties half."""
    by = by or []
    up = Window.partitionBy(*by).orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    run = _score_groups(df, by).withColumn("neg", F.col("n") - F.col("pos")).withColumn("below", F.coalesce(F.sum("neg").over(up), F.lit(0.0)))
    return run.groupBy(*by).agg(F.try_divide(F.sum(F.col("pos") * (F.col("below") + 0.5 * F.col("neg"))), F.sum("pos") * F.sum("neg")).alias("roc_auc"))


def reciprocal_ranks(df: DataFrame, ties: str = "mean") -> DataFrame:
    """query_id, step and 1 / rank of the positive among its query's rows."""
    # In one pass over the rows, which may be scored on the way: a query's candidates are one list.
    own, others = F.max(F.when(F.col("label") == 1, F.col("score"))).alias("own"), F.collect_list(F.when(F.col("label") == 0, F.col("score"))).alias("others")
    lists = df.groupBy("query_id", "step").agg(own, others).filter("own IS NOT NULL")
    counts = lists.select("query_id", "step", F.size(F.filter("others", lambda s: s > F.col("own"))).alias("above"), F.size(F.filter("others", lambda s: s == F.col("own"))).alias("level"))
    share = {"mean": 0.5, "optimistic": 0.0, "pessimistic": 1.0}[ties]
    return counts.select("query_id", "step", (1 / (1 + F.col("above") + share * F.col("level"))).alias("rr"))


def mrr(df: DataFrame, ties: str = "mean") -> DataFrame:
    """Mean over steps of the mean reciprocal rank in the step."""
    by_step = reciprocal_ranks(df, ties).groupBy("step").agg(F.avg("rr").alias("m"))
    return by_step.agg(F.avg("m").alias("mrr"))


def confusion(df: DataFrame) -> DataFrame:
    return df.groupBy("label", "predicted").agg(F.count("*").alias("n"))


def f1(df: DataFrame) -> DataFrame:
    """f1_micro and f1_macro of label and predicted."""
    c = confusion(df)
    tp = c.filter("label = predicted").select(F.col("label").alias("c"), F.col("n").alias("tp"))
    truth = c.groupBy(F.col("label").alias("c")).agg(F.sum("n").alias("n_true"))
    said = c.groupBy(F.col("predicted").alias("c")).agg(F.sum("n").alias("n_said"))
    each = truth.join(said, "c", "full").join(tp, "c", "left").select(*[F.coalesce(x, F.lit(0)).cast("double").alias(x) for x in ("tp", "n_true", "n_said")])
    return each.agg((2 * F.sum("tp") / (F.sum("n_true") + F.sum("n_said"))).alias("f1_micro"), F.avg(2 * F.col("tp") / (F.col("n_true") + F.col("n_said"))).alias("f1_macro"))


def summarise_seeds(df: DataFrame, by: list[str], metric: str) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(metric).alias("mean"), F.stddev_samp(metric).alias("std"), F.count("*").alias("n_seeds"))


def relative_gain(own: float, other: float) -> float:
    return (own - other) / other


def label_conflict_rate(labels: DataFrame) -> DataFrame:
    """The share of nodes that have more than one label."""
    per = labels.groupBy("node").agg(F.countDistinct("label").alias("k"))
    return per.agg(F.avg((F.col("k") > 1).cast("double")).alias("conflict_rate"))
