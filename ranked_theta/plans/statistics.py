"""Statistics of a query's relations and what the planner decides by them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import predicates as P
from .jointree import PlanTree, plan_tree
from .query import Query


def gather(query: Query) -> dict[P.Side, tuple[int, int]]:
    """(rows, distinct values) of each side of a comparison, from sketches: one scan for each distinct relation."""
    wanted: dict[tuple, list[P.Side]] = {}
    for p in query.predicates():
        if isinstance(p, P.Compare):
            for s in (p.left, p.right):
                atom = query.atom(s.alias)
                wanted.setdefault((id(atom.df), atom.where), []).append(s)
    out = {}
    for sides in wanted.values():
        atom = query.atom(sides[0].alias)
        df = atom.df.where(atom.where) if atom.where else atom.df
        exprs = list(dict.fromkeys(s.expr for s in sides))
        found = df.agg(F.count(F.lit(1)), *[F.approx_count_distinct(F.expr(e)) for e in exprs]).first()
        out |= {s: (found[0], found[1 + exprs.index(s.expr)]) for s in sides}
    return out


def _levels(p: P.Compare, distinct: int) -> float:
    """Rows that a side becomes where the comparison is not its term's last."""
    bits = max(1, math.ceil(math.log2(max(2, distinct))))
    return {"=": 1, "band": 1 + bits, "!=": bits}.get(p.op, bits / 2)


def edge_cost(tree: PlanTree, parent: str, child: str, stats: dict) -> float:
    """Rows that folding the child's values into the parent moves: the expected size of the edge's connector but for its last comparison."""
    total = 0.0
    for term in tree.conditions[parent, child]:
        hard = [p for p in term if isinstance(p, P.Compare) and p.op != "="]
        sides = {}
        for alias in (parent, child):
            known = [(stats[s], p) for p in term if isinstance(p, P.Compare) for s in (p.left, p.right) if s.alias == alias and s in stats]
            rows = max((r for (r, _), _ in known), default=1)
            copies = [_levels(p, d) for (_, d), p in known if p in hard]
            sides[alias] = rows * math.prod(sorted(copies)[:-1])
        # the last band asks each source in three cells, the last non-equality reads twice
        last = max(hard, key=lambda p: p.op == "band", default=None)
        total += sides[parent] * (3 if last and last.op == "band" else 1) + sides[child]
        total += (sides[parent] + sides[child]) * bool(last and last.op == "!=")
    return total


def choose_root(query: Query) -> str:
    """The atom from which the edges cost least; of equal ones the first.

    The passes sort the root's rows once more for the cut, so that its size counts too.
    """
    stats = gather(query)
    size = {a.alias: max((r for s, (r, _) in stats.items() if s.alias == a.alias), default=1) for a in query.atoms}

    def cost(root: str) -> float:
        tree = plan_tree(query, root)
        return size[root] + sum(edge_cost(tree, a, b, stats) for a, b in tree.conditions)

    return min((a.alias for a in query.atoms), key=lambda a: (cost(a), query.index(a)))


def order_predicates(term: list, distinct: dict[str, int]) -> list:
    """Equalities first, then the comparisons by the levels that they cost, the dearest last; a band goes last before any other."""
    return sorted(term, key=lambda p: (p.op != "=", p.op == "band", _levels(p, distinct.get(p.left.expr, 2)) if p.op != "band" else 0))


def selectivity(query: Query, alias: str, columns: list[str]) -> DataFrame:
    """Rows, distinct values and quartiles of join columns, from sketches in one scan."""
    df = query.atom(alias).df
    sketches = [F.struct(F.lit(c).alias("column"), F.count(c).alias("rows"), F.approx_count_distinct(c, 0.01).alias("distinct"), F.percentile_approx(F.col(c).cast("double"), [0.25, 0.5, 0.75], 10_000).alias("quartiles")) for c in columns]
    return df.agg(F.array(*sketches).alias("found")).select(F.explode("found").alias("f")).select("f.*")
