"""Dense ranks of join values, without a single-task window."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.staging import Staging
from .joins import merged

#: Whole numbers that span no more than this need no ranks: their distance to the least one will do.
DIRECT_SPAN = 1 << 22
_LOCAL = (1 << 33) - 1


def dense_rank_domain(values: DataFrame, column: str, staging: Staging, name: str) -> tuple[DataFrame, int]:
    """(val, rk): 0-based dense ranks of the distinct non-null values, and their number.

    Distinct values are range partitioned and sorted; a value's rank is its place in its
    partition and the sizes of the partitions before, of which there are few.
    """
    distinct = values.select(F.col(column).alias("val")).where("val is not null").distinct()
    n = max(1, int(values.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = distinct.repartitionByRange(n, "val").sortWithinPartitions("val").withColumn("at", F.monotonically_increasing_id())
    placed = staging.save(placed, f"{name}-placed")  # the ranges come from a sample and must not be drawn twice
    part, place = F.shiftrightunsigned("at", 33), F.col("at").bitwiseAND(F.lit(_LOCAL))
    sizes = {r["p"]: r["n"] for r in placed.groupBy(part.alias("p")).count().withColumnRenamed("count", "n").collect()}
    before, total = {}, 0
    for p in sorted(sizes):
        before[p], total = total, total + sizes[p]
    if not before:
        return placed.select("val", F.col("at").alias("rk")), 0
    offsets = F.create_map(*[F.lit(x) for p in before for x in (p, before[p])])
    return placed.select("val", (F.element_at(offsets, part) + place).cast("long").alias("rk")), total


@dataclass
class Extent:
    """What is known of a comparison's values: the least and the greatest whole number (None for other types) and how many differ, about."""

    low: int | None
    high: int | None
    distinct: int


@dataclass
class Coding:
    """Order-preserving codes from 0: a distance to the least value, or a written table of dense ranks."""

    low: int | None
    domain: DataFrame | None
    bits: int

    def apply(self, df: DataFrame, column: str) -> DataFrame:
        if self.domain is None:
            return df.withColumn(column, (F.col(column) - F.lit(self.low)).cast("long"))
        domain = self.domain.select(F.col("val").alias("_dom"), F.col("rk").alias("_rk"))
        return df.join(merged(domain), F.col(column) == F.col("_dom")).drop(column, "_dom").withColumnRenamed("_rk", column)


def extent(both: DataFrame) -> Extent:
    """Of the column v, by one scan."""
    whole = dict(both.dtypes)["v"] in ("bigint", "int", "smallint", "tinyint")
    found = both.agg(F.approx_count_distinct("v"), *([F.min("v"), F.max("v")] if whole else [])).first()
    return Extent(found[1] if whole else None, found[2] if whole else None, found[0])


def coding(both: DataFrame, known: Extent, staging: Staging, name: str, sparse: bool = True) -> Coding:
    """Codes of the column v; few values that are far apart are ranked, if ``sparse``, so that codes have few bits."""
    if known.distinct == 0:
        return Coding(0, None, 1) if known.low is None and dict(both.dtypes)["v"] in ("bigint", "int", "smallint", "tinyint") else Coding(None, dense_rank_domain(both, "v", staging, name)[0], 1)
    if known.low is not None and known.high - known.low <= DIRECT_SPAN and (not sparse or known.high - known.low < 16 * known.distinct):
        return Coding(known.low, None, max(1, (known.high - known.low).bit_length()))
    domain, n = dense_rank_domain(both, "v", staging, name)
    return Coding(None, domain, max(1, (max(n, 1) - 1).bit_length()))


def codes(s: DataFrame, t: DataFrame, left: str, right: str, staging: Staging, name: str) -> tuple[DataFrame, DataFrame, int]:
    """Both sides with their join column replaced by order-preserving codes from 0, and the bits of a code."""
    both = s.select(F.col(left).alias("v")).unionByName(t.select(F.col(right).alias("v")))
    made = coding(both, extent(both), staging, name, False)
    return made.apply(s, left), made.apply(t, right), made.bits


def balanced(rank: Column, count: int) -> Column:
    """Position of a rank in the median-pivot tree of ``count`` values, as a code whose bits are the turns taken.

    A set of d values splits at the 0-based index d // 2; the turns, padded on the right,
    form the code, by a fold over a fixed number of turns.
    """
    turns = F.sequence(F.lit(1), F.lit(max(1, (count - 1).bit_length())))
    start = F.struct(F.lit(0).cast("long").alias("low"), F.lit(count).cast("long").alias("size"), F.lit(0).cast("long").alias("code"))

    def turn(acc: Column, _: Column) -> Column:
        half = F.shiftright(acc["size"], 1)
        up = (acc["size"] > 1) & (rank >= acc["low"] + half)
        size = F.when(acc["size"] <= 1, acc["size"]).when(up, acc["size"] - half).otherwise(half)
        return F.struct(F.when(up, acc["low"] + half).otherwise(acc["low"]).alias("low"), size.alias("size"), (acc["code"] * 2 + F.when(up, 1).otherwise(0)).cast("long").alias("code"))

    return F.aggregate(turns, start, turn)["code"]
