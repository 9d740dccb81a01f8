"""How tables of unknown size are joined."""

from __future__ import annotations

from pyspark.sql import DataFrame


def merged(df: DataFrame) -> DataFrame:
    """``df`` for a join that sorts and merges.

    Spark's estimates take a row that explodes for one row and a written table for the size
    of its compressed files, so that on its own it would send millions of edges through the
    driver as a broadcast table.
    """
    return df.hint("merge")
