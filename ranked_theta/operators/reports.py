"""Summaries around ranked answers, on Spark's own operators."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def cube_sums(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Counts and sums over all subsets of keys."""
    return df.cube(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum(value).cast("long").alias("total"), F.grouping_id().cast("long").alias("level"))


def rollup_sums(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    return df.rollup(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum(value).cast("long").alias("total"))


def top_per_group(df: DataFrame, keys: list[str], order: list[str], k: int) -> DataFrame:
    """The k first rows of each group in the given order, with their place; Spark keeps k rows per group before the exchange."""
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("place", place.cast("long")).where(F.col("place") <= k)


def running(df: DataFrame, keys: list[str], order: list[str], value: str) -> DataFrame:
    """Running sum and minimum with lag, ROWS frames."""
    w = Window.partitionBy(*keys).orderBy(*order)
    upto = w.rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumns({"running_sum": F.sum(value).over(upto).cast("long"), "running_min": F.min(value).over(upto), "before": F.lag(value).over(w), "dense": F.dense_rank().over(w).cast("long")})
