"""Theta-joins as chains of equi-joins, and what follows from it: semi, anti and aggregate joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import predicates as P
from ..plans.jointree import PlanTree, plan_tree
from ..plans.query import Atom, Query
from ..sources.staging import Staging
from . import connectors, fold
from .joins import merged
from .ranked import Passes, edge_terms, key_name, prepare


#: Tasks of listed answers for each shuffle partition.
SPREAD = 2


def _pair(s: DataFrame, t: DataFrame, where: P.Condition, rid_s: str, rid_t: str, value: str | None = None) -> tuple[PlanTree, DataFrame, DataFrame, list]:
    """A two-atom query over aliases s and t with its key columns, and ``value`` of t as ``val``."""
    query = Query([Atom("s", s, rid_s, "1"), Atom("t", t, rid_t, "1")], where)
    tree = plan_tree(query, "s")
    query = tree.query
    passes = Passes(query, tree, None)
    extra = [P.Side("t", value)] if value else []
    left, right = prepare(query, "s", passes.sides("s")).drop("w"), prepare(query, "t", passes.sides("t") + extra).drop("w")
    if value:
        right = right.withColumn("val", F.col(key_name(extra[0])))
    return tree, left, right, edge_terms(tree, "s", "t")


def connector(s: DataFrame, t: DataFrame, where: P.Condition, method: str = "auto", rid_s: str = "rid", rid_t: str = "rid") -> connectors.Connector:
    """The connector graph of a condition between s and t."""
    _, left, right, terms = _pair(s, t, where, rid_s, rid_t)
    return connectors.build(left, right, terms, method)


def theta_join(s: DataFrame, t: DataFrame, where: P.Condition, method: str = "auto", rid_s: str = "rid", rid_t: str = "rid") -> DataFrame:
    """(rid_s, rid_t) of all joining pairs, without nested loops; the condition is over aliases s and t.

    A disjunction can reach a pair by several terms. Terms that exclude each other are put in
    their place, so that no pair comes twice; where that takes too many terms, or a key is
    null, the pairs are made distinct.
    """
    _, left, right, terms = _pair(s, t, where, rid_s, rid_t)
    if len(terms) > 1 and method != "direct" and not any(isinstance(p, P.Opaque) for term in terms for p, _, _ in term):
        apart = fold.disjoint(terms)
        if apart is not None and fold.without_nulls(left, right, terms):
            terms = apart
    graph = connectors.build(left, right, terms, method)
    pairs = graph.pairs()
    return pairs.dropDuplicates(["rid_s", "rid_t"]) if graph.dup_factor > 1 else pairs


def theta_agg(s: DataFrame, t: DataFrame, where: P.Condition, value: str, fn: str = "sum", out: str = "agg", rid_s: str = "rid", rid_t: str = "rid", ranges: int | None = None) -> DataFrame:
    """For each row of s the min, max, sum or count over the joining rows of t, without the join; rows without partner drop out."""
    kind = {"min": "min", "max": "min", "sum": "sum", "count": "sum"}[fn]
    expr = {"min": value, "max": f"-({value})", "sum": value, "count": "CAST(1 AS BIGINT)"}[fn]
    _, left, right, terms = _pair(s, t, where, rid_s, rid_t, expr)
    found = fold.fold(left, right, terms, kind, "agg_", Staging(s.sparkSession, "agg"), "agg", ranges)
    return found.select("rid", (-F.col("agg_") if fn == "max" else F.col("agg_")).alias(out))


def theta_semi(s: DataFrame, t: DataFrame, where: P.Condition, anti: bool = False, rid_s: str = "rid", rid_t: str = "rid", ranges: int | None = None) -> DataFrame:
    """Rows of s with a partner in t (or, ``anti``, without one)."""
    _, left, right, terms = _pair(s, t, where, rid_s, rid_t)
    right = right.withColumn("val", F.lit(1))
    have = fold.fold(left.select("rid", *[c for c in left.columns if c != "rid"]), right, terms, "min", "has", Staging(s.sparkSession, "semi"), "semi", ranges).select(F.col("rid").alias("_has"))
    return s.join(have, F.expr(rid_s) == F.col("_has"), "left_anti" if anti else "left_semi")


def reduce_query(query: Query, method: str = "auto", root: str | None = None) -> dict[tuple[str, str], connectors.Connector]:
    """Connectors of all edges of an acyclic query: with them the query has equalities only."""
    tree = plan_tree(query, root)
    query = tree.query
    passes = Passes(query, tree, None)
    out = {}
    for parent, child in tree.conditions:
        left, right = (prepare(query, a, passes.sides(a)).drop("w") for a in (parent, child))
        out[parent, child] = connectors.build(left, right, edge_terms(tree, parent, child), method, f"{parent}-{child}")
    return out


def _unfolded(out: DataFrame, alias: str) -> DataFrame:
    """A row for each element of an atom's fan; few of them at once, as in ``connectors._dealt``."""
    others = [c for c in out.columns if c != f"fan_{alias}"]
    out = out.select(*others, F.arrays_zip(f"fan_{alias}.rid_t", f"fan_{alias}.w_{alias}").alias("_all"))
    out = out.select(*others, F.explode(connectors._cut("_all", 16)).alias("_some")).select(*others, F.explode("_some").alias("_one"))
    return out.select(*others, F.col("_one.rid_t").alias(f"rid_{alias}"), F.col(f"_one.w_{alias}"))


def enumerate_all(query: Query, method: str = "auto") -> DataFrame:
    """weight and rid_1.. of all answers of an acyclic query, by equi-joins.

    The root is the atom with most neighbours, whose partners come to its rows in arrays. An
    array becomes rows where a further atom joins its elements, or at the end: pairs, and
    still more the answers, are not shuffled row by row.
    """
    tree = plan_tree(query)
    root = max(tree.preorder(), key=lambda a: len(tree.children[a]) + (a != tree.root))
    tree = plan_tree(query, root)
    query = tree.query
    edges = reduce_query(query, method, root)
    names, folded = [a.alias for a in query.atoms], []
    rows = lambda alias: prepare(query, alias, []).select(F.col("rid").alias(f"rid_{alias}"), F.col("w").alias(f"w_{alias}"))
    # in small tasks: a row has many more answers than Spark sees in its size
    tasks = SPREAD * max(1, int(query.atoms[0].df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    out = rows(root).repartition(tasks, f"rid_{root}")
    for alias in tree.preorder()[1:]:
        parent, graph = tree.parent(alias), edges[tree.parent(alias), alias]
        if parent in folded:
            folded.remove(parent)
            out = _unfolded(out, parent)
        # weights go with the edges, so that the answers, which are many more, meet no further table
        graph.carry(rows(alias).withColumnRenamed(f"rid_{alias}", "rid_t"))
        if graph.dup_factor > 1:
            fans = connectors.one_by_one(graph.pairs((f"w_{alias}",)).distinct(), (f"w_{alias}",))
        else:
            fans = graph.fans((f"w_{alias}",))
        out = out.join(merged(fans.withColumnsRenamed({"rid_s": f"rid_{parent}", "fan": f"fan_{alias}"})), f"rid_{parent}")
        folded.append(alias)
    for alias in folded:
        out = _unfolded(out, alias)
    total = query.rank.shown(query.rank.combine([F.col(f"w_{n}") for n in names]))
    return out.select(total.alias("weight"), *[F.col(f"rid_{n}").alias(f"rid_{i + 1}") for i, n in enumerate(names)])
