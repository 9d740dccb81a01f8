"""Where relations, connectors and answers go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(df: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite", **options) -> None:
    if kind not in ("parquet", "orc", "csv", "json"):
        raise ValueError(f"unknown kind {kind}")
    writer = df.write.mode(mode).options(**options).format(kind)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, table: str, keys: list[str], buckets: int, mode: str = "overwrite") -> None:
    """A bucketed table, so that later joins on the keys need no exchange."""
    df.write.mode(mode).format("parquet").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def write_connector(graph, path: str) -> None:
    """The edge relations of a connector, one folder each."""
    for k, part in enumerate(graph.parts):
        part.write.mode("overwrite").parquet(f"{path}/part{k}")
