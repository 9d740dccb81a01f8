"""Derived views of the given tables, in Spark and as DuckDB text for the oracles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_CENTS = "CAST(round({0} * 100) AS BIGINT)"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: str) -> Column:
    """A money column as an exact whole number."""
    return F.expr(_CENTS.format(column))


#: Key, second key and amount of the tables that give a relation of two whole columns and a weight.
NUMBERS = {"orders": ("o_orderkey", "o_custkey", "o_totalprice"), "customer": ("c_custkey", "c_nationkey", "c_acctbal"), "supplier": ("s_suppkey", "s_nationkey", "s_acctbal"), "part": ("p_partkey", "p_size", "p_retailprice")}


def slices(spark: SparkSession, sf_dir: str, source: str = "orders", domain: int = 10_000) -> DataFrame:
    """rid, a, b, w from all rows of a table: two whole columns in [0, domain) and an exact weight."""
    key, other, amount = NUMBERS[source]
    cents = _CENTS.format(amount)
    return table(spark, sf_dir, source).selectExpr(f"{key} AS rid", f"({key} * 7919 + CAST({other} AS BIGINT) * 104729) % 10000 % {domain} AS a", f"pmod({cents}, 10000L) % {domain} AS b", f"{cents} AS w")


def slices_sql(source: str = "orders", domain: int = 10_000) -> str:
    key, other, amount = NUMBERS[source]
    cents = _CENTS.format(amount)
    return f"SELECT {key} AS rid, ({key} * 7919 + {other}::BIGINT * 104729) % 10000 % {domain} AS a, (({cents} % 10000) + 10000) % 10000 % {domain} AS b, {cents} AS w FROM {source}"


def sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rid (struct), supp, qty, ship, commit_, receipt (whole days or microseconds), w, line from lineitem."""
    ship = "unix_seconds(CAST(l_shipdate AS TIMESTAMP))"
    return table(spark, sf_dir, "lineitem").selectExpr(
        f"struct(l_orderkey, CAST(l_linenumber AS BIGINT) AS l_linenumber, l_partkey, l_suppkey, {ship} AS ship, CAST(l_quantity AS BIGINT) AS qty) AS rid",
        "l_suppkey AS supp",
        "CAST(l_quantity AS BIGINT) AS qty",
        f"{ship} AS ship",
        f"{ship} + 86400 * ((l_orderkey * 7 + l_linenumber * 13) % 61 - 30) AS commit_",
        f"{ship} + 86400 * (1 + (l_partkey * 11 + l_linenumber * 17) % 30) AS receipt",
        f"{_CENTS.format('l_extendedprice')} AS w",
        "CAST(l_linenumber AS BIGINT) AS line",
    )


def sales_sql() -> str:
    ship = "CAST(epoch(l_shipdate) AS BIGINT)"
    return (
        f"SELECT row(l_orderkey, l_linenumber::BIGINT, l_partkey, l_suppkey, {ship}, l_quantity::BIGINT) AS rid, "
        f"concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, {ship}, l_quantity::BIGINT) AS rid_text, l_suppkey AS supp, l_quantity::BIGINT AS qty, {ship} AS ship, "
        f"{ship} + 86400 * ((l_orderkey * 7 + l_linenumber * 13) % 61 - 30) AS commit_, {ship} + 86400 * (1 + (l_partkey * 11 + l_linenumber * 17) % 30) AS receipt, "
        f"{_CENTS.format('l_extendedprice')} AS w, l_linenumber::BIGINT AS line FROM lineitem"
    )


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rid, src, dst, ts (us), s, r and prob (parts per million) from events: a temporal graph."""
    rows = table(spark, sf_dir, "events").selectExpr("event_id AS rid", "user_id AS src", "try_cast(get_json_object(props, '$.k') AS BIGINT) AS dst", "unix_micros(CAST(ts AS TIMESTAMP)) AS ts", f"{_CENTS.format('value')} AS s", "(event_id * 7919) % 10007 AS r")
    pair, out = rows.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n_pair")), rows.groupBy("src").agg(F.count(F.lit(1)).alias("n_src"))
    prob = pair.join(out, "src").select("src", "dst", F.expr("1000000 * n_pair DIV n_src").alias("prob"))
    return rows.join(prob, ["src", "dst"], "left")


def edges_sql() -> str:
    return (
        f"SELECT *, 1000000 * count(*) OVER (PARTITION BY src, dst) // count(*) OVER (PARTITION BY src) AS prob FROM (SELECT event_id AS rid, user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, epoch_us(ts) AS ts, {_CENTS.format('value')} AS s, (event_id * 7919) % 10007 AS r FROM events)"
    )


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rid, x (us), y, w from events."""
    return table(spark, sf_dir, "events").selectExpr("event_id AS rid", "unix_micros(CAST(ts AS TIMESTAMP)) AS x", f"{_CENTS.format('value')} AS y", f"{_CENTS.format('value')} AS w")


def points_sql() -> str:
    return f"SELECT event_id AS rid, epoch_us(ts) AS x, {_CENTS.format('value')} AS y, {_CENTS.format('value')} AS w FROM events"


def places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rid, x, y (millionths), w from two components of embeddings."""
    scaled = "CAST(round(CAST(embedding[{0}] AS DOUBLE) * 1000000) AS BIGINT)"
    return table(spark, sf_dir, "embeddings").selectExpr("vec_id AS rid", f"{scaled.format(0)} AS x", f"{scaled.format(1)} AS y", "CAST(label AS BIGINT) AS w")


def places_sql() -> str:
    scaled = "CAST(round(CAST(embedding[{0}] AS DOUBLE) * 1000000) AS BIGINT)"
    return f"SELECT vec_id AS rid, {scaled.format(1)} AS x, {scaled.format(2)} AS y, label::BIGINT AS w FROM embeddings"
