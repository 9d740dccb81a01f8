"""Python functions that SQL and DataFrame users can call: the enumerator as a table function, user rankings, opaque predicates."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DataType

from ..operators import anyk, stacked
from ..plans.query import Query


def pack(query: Query, k: int, method: str = "auto") -> str:
    """The reduced graph of a query for its k best answers as text: at most k rows of each atom and their edges."""
    if query.rank.name != "sum":
        raise ValueError("packed graphs are for sums of whole weights")
    g = stacked.stack(query, method)
    if g.passes.named:
        raise ValueError("packed graphs are for whole numbers as ids")
    made = stacked.instance(g, k)
    lists = [[[int(x), [int(t) for t in ts]] for x, ts in one.items()] for one in made.lists]
    sign = -1 if query.rank.desc else 1
    return json.dumps({"parents": made.parents, "rows": [[[None if w is None else int(w), rid] for w, rid in rows] for rows in made.rows], "lists": lists, "order": made.order, "sign": sign})


def unpack(text: str) -> tuple[anyk.Instance, int]:
    held = json.loads(text)
    nodes = [{x: ts for x, ts in one} for one in held["lists"]]
    return anyk.Instance(held["parents"], [[tuple(r) for r in rows] for rows in held["rows"]], [{x: x for x in one} for one in nodes], nodes, held["order"]), held["sign"]


class RankedJoin:
    """Table function (rank, weight, ids) over a packed graph: its k best answers, one by one."""

    def eval(self, graph: str, k: int) -> Iterator[tuple]:
        if graph is None or k is None:
            return
        made, sign = unpack(graph)
        for n, (w, ids) in enumerate(stacked.dedupe(anyk.enumerate_answers(made)), 1):
            if n > k:
                return
            yield n, sign * w, list(ids)


def register(spark: SparkSession) -> None:
    """Makes ``ranked_join(graph, k)`` known to SQL."""
    spark.udtf.register("ranked_join", F.udtf(RankedJoin, returnType="rank long, weight long, ids array<long>"))


def least_by(score: Callable[[pd.Series], pd.Series], returns: str | DataType = "double"):
    """An aggregate for rankings of the user's own: the least score of a group's values.

    Rows of a group come together in one worker, so that groups should be of bounded size;
    nulls are left out, and a group of nulls has null.
    """

    @F.pandas_udf(returns)
    def best(values: pd.Series) -> float:
        known = values.dropna()
        return None if known.empty else score(known).min()

    return best


def predicate(spark: SparkSession, name: str, test: Callable[[pd.Series, pd.Series], pd.Series]) -> str:
    """Registers a vectorised test on two columns for use in ``predicates.opaque``; null on either side is false."""

    @F.pandas_udf("boolean")
    def held(a: pd.Series, b: pd.Series) -> pd.Series:
        known = a.notna() & b.notna()
        return known & test(a.where(known, 0), b.where(known, 0)).astype(bool)

    spark.udf.register(name, held)
    return name


def enumerated(spark: SparkSession, query: Query, k: int) -> DataFrame:
    """The k best answers through the table function, as SQL would call it."""
    register(spark)
    packed = spark.createDataFrame([(pack(query, k),)], "graph string")
    packed.createOrReplaceTempView("packed_graph")
    found = spark.sql(f"SELECT r.rank, r.weight, r.ids FROM packed_graph, LATERAL ranked_join(graph, {int(k)}) r")
    return found.select("rank", "weight", *[F.col("ids")[i].alias(f"rid_{i + 1}") for i in range(len(query.atoms))])
