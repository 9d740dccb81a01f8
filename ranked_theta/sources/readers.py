"""Relations from files, tables, rows and a generator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, columns: list[str] | None = None, **options) -> DataFrame:
    """Parquet or ORC as they are; CSV and JSON with an explicit schema, never inferred."""
    if kind not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"unknown kind {kind}")
    if kind in ("csv", "json") and schema is None:
        raise ValueError("text formats need a schema")
    reader = spark.read.options(**options)
    df = (reader.schema(schema) if schema else reader).format(kind).load(path)
    return df.select(*columns) if columns else df


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)


def synthetic(spark: SparkSession, n: int, seed: int, domain: int = 10_000) -> DataFrame:
    """rid, a, b in [0, domain), w; rows equal in a, b and w come once."""
    made = spark.range(n).select(F.floor(F.rand(seed) * domain).cast("long").alias("a"), F.floor(F.rand(seed + 1) * domain).cast("long").alias("b"), F.floor(F.rand(seed + 2) * 1_000_000_000).cast("long").alias("w"), F.col("id").alias("rid"))
    return made.groupBy("a", "b", "w").agg(F.min("rid").alias("rid")).select("rid", "a", "b", "w")


def stream(spark: SparkSession, path: str, schema, kind: str = "parquet", files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema).format(kind)
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).load(path)
