"""Projections of ranked answers."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import predicates as P
from ..plans.jointree import covered, plan_tree
from ..plans.query import Atom, Query
from . import ranked


def project_bag(query: Query, head: dict[str, list[str]], k: int) -> DataFrame:
    """rank, weight and head columns of the k best answers; equal rows stay apart."""
    found = ranked.materialize(ranked.top_k(query, k), query, head)
    return found.select("rank", "weight", *[f"{a}_{c}" for a, cs in head.items() for c in cs])


def is_free_connex(query: Query, head: list[str], root: str | None = None) -> bool:
    """Whether the atoms of the head form a subtree that contains the root of a plan tree."""
    tree = plan_tree(query, root or head[0])
    return tree.root in head and all(tree.parent(a) in head for a in head if a != tree.root)


def project_free_connex(query: Query, alias: str, columns: list[str], k: int) -> DataFrame:
    """Distinct values of columns of one atom with the least weight of an answer that has them.

    The atom is the root; all others are folded into it, and its rows are grouped.
    """
    atom = query.atom(alias)
    best = ranked.dp_values(query, alias, root=alias)
    rows = atom.df.select(F.expr(atom.rid).alias("rid"), *columns).join(best, "rid")
    lift = -F.col("best") if query.rank.desc else F.col("best")
    groups = rows.groupBy(*columns).agg(F.min(lift).alias("_w")).orderBy("_w", *columns).limit(k)
    return groups.select(F.row_number().over(Window.orderBy("_w", *columns)).cast("long").alias("rank"), query.rank.shown(F.col("_w")).alias("weight"), *columns)


def project_head(query: Query, head: dict[str, list[str]], k: int) -> DataFrame:
    """As ``project_free_connex`` for a head of several atoms that form a subtree with the root.

    All other atoms are folded into the head's; equal head rows of an atom are one, with
    the least weight, and the query over them has an answer for each head row. The keys
    that join the head's atoms must be columns of the head.
    """
    query = query.routed()
    names = list(head)
    if not is_free_connex(query, names, names[0]):
        raise ValueError("the head's atoms are no subtree of the plan tree")
    passes = ranked._passes(query, names[0])
    passes.bottom_up()
    tree, atoms, kept = passes.tree, [], []
    inner = {(a, b) for a, b in tree.conditions if a in head and b in head}
    for a, b in inner:
        for term in tree.conditions[a, b]:
            for p in term:
                for s in (p.left, p.right):
                    if s.expr not in head[s.alias]:
                        raise ValueError(f"{s.alias}.{s.expr} joins atoms of the head and is not in it")
    for alias in names:
        atom = query.atom(alias)
        outside = [(tree.subtree(c), F.col(f"m_{c}")) for c in tree.children[alias] if c not in head]
        found = passes.up[alias].withColumn("_v", passes.value([passes.own(alias)], outside)["w"])
        best = passes.name_rows(found.select("rid", query.rank.shown(F.col("_v")).alias("_w")), {"rid": alias})
        rows = (atom.df.where(atom.where) if atom.where else atom.df).select(F.expr(atom.rid).alias("rid"), *head[alias]).join(best, "rid")
        least = F.max("_w") if query.rank.desc else F.min("_w")
        rows = passes.staging.save(rows.groupBy(*head[alias]).agg(least.alias("_w")), f"head-{alias}")
        atoms.append(Atom(alias, rows, f"struct({', '.join(head[alias])})", "_w"))
    for c in query.conjuncts():
        if covered(c) <= set(names):
            kept.append(c)
    found = ranked.top_k(replace(query, atoms=atoms, where=P.all_of(*kept)), k)
    columns = [F.col(f"rid_{i + 1}.{c}").alias(f"{a}_{c}") for i, a in enumerate(names) for c in head[a]]
    return found.select("rank", "weight", *columns)


def project_distinct(query: Query, head: dict[str, list[str]], k: int) -> DataFrame:
    """k distinct head rows by the weight of their best answer, from as many answers as it takes."""
    names = [f"{a}_{c}" for a, cs in head.items() for c in cs]
    passes, asked = ranked._passes(query, None), max(2 * k, 2)
    while True:
        passes.cut(asked)
        found = passes.staging.save(passes.answers(passes.beam(asked), asked), f"answers-{asked}")
        rows = ranked.materialize(found, query, head)
        distinct = passes.staging.save(rows.groupBy(*names).agg(F.min("rank").alias("_r"), F.min(F.struct("rank", "weight"))["weight"].alias("weight")), f"distinct-{asked}")
        if distinct.count() >= k or found.count() < asked:
            break
        asked *= 4
    return distinct.orderBy("_r").limit(k).select(F.row_number().over(Window.orderBy("_r")).cast("long").alias("rank"), "weight", *names)
