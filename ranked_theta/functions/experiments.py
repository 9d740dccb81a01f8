"""The experiments: what each method finds at each point of a sweep, with SQL that says the same.

A point is a workload with its parameter. Its row has the size of the join and, for a
method and k, how many answers were found and the weights of the first and the last one.
Times of the same points are measured by ``bench.py``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, ranked, stacked
from ..plans.query import Query
from . import workloads as W

#: Ways to the k best answers that a point can be asked for.
METHODS: dict[str, Callable[[Query, int], DataFrame]] = {
    "factorised": ranked.top_k,
    "binary": lambda q, k: stacked.any_k(q, k, method="binary"),
    "median": lambda q, k: stacked.any_k(q, k, method="median"),
    "multiway": lambda q, k: stacked.any_k(q, k, method="multiway"),
    "two-way": lambda q, k: stacked.any_k(q, k, method="two-way"),
    "direct-equi": baselines.direct_equi,
    "materialize": baselines.materialize_rank,
    "sort": lambda q, k: baselines.materialize_rank(q, k, "sort"),
    "native-sql": baselines.native_sql,
}


@dataclass(frozen=True)
class Point:
    """``value``: the parameter, as text; ``methods`` each give the k best answers for each of ``ks``."""

    workload: str
    value: str
    work: W.Workload
    ks: tuple[int, ...] = (1000,)
    methods: tuple[str, ...] = ("factorised",)

    def rows(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        query = self.work.query(spark, sf_dir)
        answers = ranked.count_answers(query, exact=True).first()["answers"]
        out = []
        for method in self.methods:
            if method == "factorised" and max(self.ks) > 1:  # one bottom-up pass for all k
                passes = ranked._passes(query, None)

                def run(query: Query, k: int, passes: ranked.Passes = passes) -> DataFrame:
                    passes.cut(k)
                    return passes.answers(passes.beam(k), k)
            else:
                run = METHODS[method]
            for k in self.ks:
                top = run(query, k).agg(F.count(F.lit(1)), F.min_by("weight", "rank"), F.max_by("weight", "rank")).first()
                out.append((self.workload, self.value, len(query.atoms), method, k, str(answers), *(None if x is None else int(x) for x in top)))
        return spark.createDataFrame(out, "workload string, value string, length long, method string, k long, answers string, found long, first long, last long")

    def sql(self) -> str:
        size = f"(SELECT CAST(answers AS VARCHAR) FROM ({self.work.count_sql()}))"
        methods = ", ".join(f"('{m}')" for m in self.methods)
        parts = []
        for k in self.ks:
            top = f"(SELECT count(*)::BIGINT AS found, arg_min(weight, rank)::BIGINT AS first, arg_max(weight, rank)::BIGINT AS last FROM ({self.work.oracle(k)}))"
            parts.append(f"SELECT '{self.workload}' AS workload, '{self.value}' AS value, {self.work.length}::BIGINT AS length, m.method, {k}::BIGINT AS k, {size} AS answers, t.* FROM (VALUES {methods}) m(method), {top} t")
        return " UNION ALL ".join(parts)


def sweep(points: list[Point]) -> tuple[Callable[[SparkSession, str], DataFrame], str]:
    """A query over all points, one after another, and its SQL."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for p in points:
            one = p.rows(spark, sf_dir)
            out = one if out is None else out.unionByName(one)
        return out

    return run, " UNION ALL ".join(p.sql() for p in points)


#: Tables that give the synthetic relation, by size.
SIZES = ("supplier", "customer", "part", "orders")


def size_points(workload: str) -> list[Point]:
    """Relations of growing size, lengths 2 and 4; the line items are one size for each scale factor."""
    if workload in ("w3", "w4"):
        return [Point(workload, "lineitem", (W.sales_rise if workload == "w3" else W.sales_any_date)(3))]
    make = W.chain_inequality if workload == "w1" else W.chain_band
    return [Point(workload, x, make(n, x)) for n in (2, 4) for x in SIZES if n == 2 or x != "orders"]


def length_points(workload: str) -> list[Point]:
    """Path queries of lengths 2 to 10; k up to a million for the short ones."""
    make = W.temporal_paths if workload == "w5" else W.falling_paths
    return [Point(workload, str(n), make(n), (1, 1000, 1_000_000) if n <= 3 else (1000,)) for n in range(2, 11)]


def width_points() -> list[Point]:
    return [Point("w7", str(10_000 * 2**j), W.near_places(10_000 * 2**j)) for j in range(6)]


def domain_points() -> list[Point]:
    return [Point("w1", str(2**j), W.chain_inequality(2, domain=2**j), (1,)) for j in (4, 8, 12)]


def method_points() -> list[Point]:
    """Methods at the same points, small enough for those that list all pairs."""
    every = ("factorised", "binary", "median", "multiway", "two-way", "direct-equi", "materialize", "sort", "native-sql")
    return [Point("w1", "supplier", W.chain_inequality(2, "supplier"), (500,), every), Point("w2", "customer", W.chain_band(2, "customer"), (500,), ("factorised", "multiway", "native-sql")), Point("w5", "2", W.temporal_paths(2), (1, 500), ("factorised", "materialize", "sort"))]
