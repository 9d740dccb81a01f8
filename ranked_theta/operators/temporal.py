"""As-of and interval joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import predicates as P
from .equireduce import theta_join


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, columns: list[str], strict: bool = False) -> DataFrame:
    """Rows of ``left`` with ``columns`` of the last row of ``right`` at or before (``strict``: before) their time, per key.

    Both sides are sorted together once; ties among right rows at one time go to the
    largest value of the columns. Rows without a match get nulls.
    """
    value = F.struct(*[F.col(c) for c in columns])
    a = left.select(F.col(key).alias("_k"), F.col(at).alias("_t"), F.lit(0 if strict else 1).alias("_side"), F.struct(*left.columns).alias("_row"))
    b = right.select(F.col(key).alias("_k"), F.col(at).alias("_t"), F.lit(1 if strict else 0).alias("_side"), value.alias("_v"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy("_k").orderBy("_t", "_side", F.col("_v").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("_m", F.last("_v", True).over(w)).where("_row is not null")
    return found.select("_row.*", *[F.col(f"_m.{c}").alias(f"asof_{c}") for c in columns])


def interval_join(left: DataFrame, right: DataFrame, start: str, end: str, key: str | None = None, rid_s: str = "rid", rid_t: str = "rid") -> DataFrame:
    """(rid_s, rid_t) of half-open intervals that overlap: two inequalities, reduced to equi-joins."""
    where = P.lt(("s", start), ("t", end)) & P.gt(("s", end), ("t", start))
    if key:
        where = P.eq(("s", key), ("t", key)) & where
    return theta_join(left, right, where, "binary", rid_s, rid_t)
