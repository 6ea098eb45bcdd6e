"""Joins on keys of which some hold a great share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def salted_join(big: DataFrame, small: DataFrame, key: str, hot_rows: int, slices: int, how: str = "inner") -> DataFrame:
    """Join where ``big`` has hot keys: their rows are dealt to ``slices``, and the other side's rows repeated for them.

    Keys with at most ``hot_rows`` rows keep one slice.  ``small`` has to be the
    side without extra rows in the result (inner or left joins of ``big``).
    """
    hot = big.groupBy(key).count().filter(F.col("count") > hot_rows).select(key, F.lit(True).alias("_hot"))
    one = big.join(hot, key, "left").withColumn("_slice", F.when(F.col("_hot"), F.pmod(F.xxhash64(*big.columns), F.lit(slices)).cast("int")).otherwise(0)).drop("_hot")
    two = small.join(hot, key, "left").withColumn("_slice", F.explode(F.when(F.col("_hot"), F.sequence(F.lit(0), F.lit(slices - 1))).otherwise(F.array(F.lit(0))))).drop("_hot")
    return one.join(two, [key, "_slice"], how).drop("_slice")
