"""What the planner decides for a query, as rows."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..operators import ranked
from . import statistics
from .jointree import plan_tree
from .predicates import Compare
from .query import Query


def method_of(term: list) -> str:
    """How an edge's term is handled by default."""
    hard = [p for p in term if not (isinstance(p, Compare) and p.op == "=")]
    if not hard:
        return "group"
    if any(not isinstance(p, Compare) for p in hard):
        return "direct"
    return "multiway" if len(hard) == 1 and hard[0].op != "band" else "binary"


def explain_ranked(query: Query, k: int) -> DataFrame:
    """(parent, child, terms, methods, rows_parent, rows_child, live_child, kept_child) for each edge of the plan tree."""
    spark = query.atoms[0].df.sparkSession
    tree = plan_tree(query)
    passes = ranked._passes(query, tree.root)
    passes.cut(k)
    rows = []
    for (parent, child), terms in tree.conditions.items():
        size = {a: passes.rows(a).count() for a in (parent, child)}
        rows.append((parent, child, len(terms), ",".join(method_of(t) for t in terms), size[parent], size[child], passes.up[child].count(), passes.reduced[child].count()))
    return spark.createDataFrame(rows, "parent string, child string, terms int, methods string, rows_parent long, rows_child long, live_child long, kept_child long")


def root_costs(query: Query) -> DataFrame:
    """(root, cost, chosen): rows that the planner expects the passes to move from each root."""
    stats, best = statistics.gather(query), statistics.choose_root(query)
    rows = []
    for atom in query.atoms:
        tree = plan_tree(query, atom.alias)
        rows.append((atom.alias, float(sum(statistics.edge_cost(tree, a, b, stats) for a, b in tree.conditions)), atom.alias == best))
    return query.atoms[0].df.sparkSession.createDataFrame(rows, "root string, cost double, chosen boolean")
