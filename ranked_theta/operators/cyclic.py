"""Cyclic theta-joins: by a filter on a ranked acyclic stream, by equi-joins, or over bags."""

from __future__ import annotations

from dataclasses import replace
from itertools import combinations
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import predicates as P
from ..plans import statistics
from ..plans.jointree import CyclicQuery, NotCovered, covered, is_acyclic
from ..plans.query import Atom, Query
from ..sources.staging import Staging
from . import ranked
from .equireduce import connector, theta_join


def often(c: P.Condition, stats: dict) -> float:
    """The share of pairs for which a condition is expected to hold, from distinct values of its sides."""
    none = 1.0
    for term in P.to_dnf(c):
        share = 1.0
        for p in term:
            if isinstance(p, P.Opaque):
                share *= 0.5
                continue
            distinct = max([stats[s][1] for s in (p.left, p.right) if s in stats], default=100)
            one = 1 / max(1, distinct)
            share *= {"=": one, "!=": 1 - one, "band": min(1.0, 2 * (p.eps or 1) * one)}.get(p.op, 0.5)
        none *= 1 - share
    return 1 - none


def split(query: Query, stats: dict | None = None) -> tuple[Query, list[P.Condition]]:
    """The query without the fewest conjuncts that make it cyclic, and those.

    Of equally many those go that hold most often (by ``stats`` of the relations, if given),
    so that the filter drops least; then the ones listed last.
    """
    query = query.routed()
    parts = query.conjuncts()
    share = [often(c, stats or {}) for c in parts]
    for n in range(len(parts)):
        choices = sorted(combinations(range(len(parts) - 1, -1, -1), n), key=lambda gone: -prod(share[i] for i in gone))
        for gone in choices:
            kept = [c for i, c in enumerate(parts) if i not in gone]
            if any(len(covered(c)) > 2 for c in kept) or not kept:
                continue
            candidate = replace(query, where=P.all_of(*kept))
            if is_acyclic(candidate):
                return candidate, [parts[i] for i in gone]
    raise CyclicQuery("no part of the condition is acyclic")


def _holds(found: DataFrame, query: Query, conditions: list[P.Condition]) -> DataFrame:
    """Answers for which the conditions hold; key values are looked up by row id."""
    sides: dict[str, list] = {}
    for c in conditions:
        for term in P.to_dnf(c):
            for p in term:
                for s in (p.left, p.right):
                    sides.setdefault(s.alias, []).append(s)
    for alias, wanted in sides.items():
        i, atom = query.index(alias) + 1, query.atom(alias)
        keys = atom.df.select(F.expr(atom.rid).alias(f"rid_{i}"), *[F.expr(s.expr).alias(f"{alias}_{ranked.key_name(s)}") for s in dict.fromkeys(wanted)])
        found = keys.join(F.broadcast(found), f"rid_{i}")  # as many rows as answers were asked for
    for c in conditions:
        either = None
        for term in P.to_dnf(c):
            both = F.lit(True)
            for p in term:
                both = both & P.to_column(p, F.col(f"{p.left.alias}_{ranked.key_name(p.left)}"), F.col(f"{p.right.alias}_{ranked.key_name(p.right)}"))
            either = both if either is None else either | both
        found = found.where(either)
    return found


def cyclic_filter(query: Query, k: int) -> DataFrame:
    """Top k by dropping conjuncts until the rest is acyclic and filtering its ranked answers, as many as it takes."""
    easy, conditions = split(query, statistics.gather(query))
    names = [f"rid_{i + 1}" for i in range(len(query.atoms))]
    passes, asked = ranked._passes(easy, None), max(2 * k, 2)
    while True:
        passes.cut(asked)
        found = passes.staging.save(passes.answers(passes.beam(asked), asked), f"answers-{asked}")
        good = passes.staging.save(_holds(found, easy, conditions).select("rank", "weight", *names), f"good-{asked}")
        if good.count() >= k or found.count() < asked:
            break
        asked *= 4
    place = Window.orderBy("rank")
    return good.orderBy("rank").limit(k).withColumn("rank", F.row_number().over(place).cast("long"))


def theta_graph(query: Query) -> dict[frozenset, list[P.Condition]]:
    """The conjuncts by the pair of atoms they need; raises NotCovered for wider ones."""
    out: dict[frozenset, list] = {}
    for c in query.conjuncts():
        needed = covered(c)
        if len(needed) != 2:
            raise NotCovered(f"a predicate needs the atoms {sorted(needed)}")
        out.setdefault(needed, []).append(c)
    return out


def _renamed(c: P.Condition, names: dict[str, str]) -> P.Condition:
    if isinstance(c, P.Compare):
        return P.Compare(c.op, P.Side(names[c.left.alias], c.left.expr), P.Side(names[c.right.alias], c.right.expr), c.eps)
    if isinstance(c, P.Negated):
        return P.Negated(_renamed(c.a, names))
    return type(c)(_renamed(c.a, names), _renamed(c.b, names))


def cyclic_to_equijoin(query: Query, method: str = "binary") -> DataFrame:
    """rid_1.. of all answers of a cyclic query by equi-joins of the edge relations of its theta graph."""
    edges = theta_graph(query)
    order = [a.alias for a in query.atoms]
    frames = {a.alias: (a.df.where(a.where) if a.where else a.df) for a in query.atoms}
    out, seen = None, set()
    pending = sorted(edges, key=lambda e: sorted(order.index(a) for a in e))
    while pending:
        pair = next((e for e in pending if not seen or e & seen), None)
        if pair is None:
            raise CyclicQuery("the theta graph is not connected")
        pending.remove(pair)
        a, b = sorted(pair, key=order.index)
        if b in seen and a not in seen:
            a, b = b, a
        graph = connector(frames[a], frames[b], _renamed(P.all_of(*edges[pair]), {a: "s", b: "t"}), method, query.atom(a).rid, query.atom(b).rid)
        if graph.dup_factor > 1 or len(graph.parts) == 1 or not {a, b} <= seen:
            pairs = graph.pairs().distinct() if graph.dup_factor > 1 else graph.pairs()
            pairs = pairs.withColumnsRenamed({"rid_s": f"rid_{a}", "rid_t": f"rid_{b}"})
            out = pairs if out is None else out.join(pairs, [f"rid_{x}" for x in (a, b) if x in seen])
        else:  # closes a cycle: the node is one more shared attribute
            for k, p in enumerate(graph.parts):
                p = p.withColumnsRenamed({"rid_s": f"rid_{a}", "rid_t": f"rid_{b}"} | {c: f"_n{k + (c != p.columns[0])}" for c in p.columns if not c.startswith("rid_")})
                out = out.join(p, [c for c in p.columns if c in out.columns])
            out = out.drop(*[c for c in out.columns if c.startswith("_n")])
        seen |= {a, b}
    return out.select(*[F.col(f"rid_{a}").alias(f"rid_{i + 1}") for i, a in enumerate(order)])


def cyclic_ranked(query: Query, k: int, method: str = "auto") -> DataFrame:
    """Top k over a decomposition: bags of two atoms, materialised by theta-joins, until the rest is acyclic.

    Neighbouring atoms are preferred as bags, so that ties break in the order of the atoms.
    A bag of a bag holds three atoms, and so on; the cost is that of the bags' joins.
    """
    query = query.routed()
    names = [a.alias for a in query.atoms]
    places = {n: (n, "") for n in names}  # the atom that holds an id now, and where in its id
    bags = 0
    while not is_acyclic(query):
        held = [a.alias for a in query.atoms]
        pairs = [(held[i], held[i + gap]) for gap in range(1, len(held)) for i in range(len(held) - gap)]
        made = [(a, b, x) for a, b in pairs if (x := _bagged(query, a, b, f"bag{bags}")) is not None]
        if not made:
            raise CyclicQuery("no two atoms make a bag")
        a, b, _ = chosen = next((m for m in made if is_acyclic(m[2])), made[0])
        query = _filled(query, *chosen, f"bag{bags}", method)
        places = {n: (f"bag{bags}", (".a" if x == a else ".b") + path) if x in (a, b) else (x, path) for n, (x, path) in places.items()}
        bags += 1
    found = ranked.top_k(query, k)
    held = [a.alias for a in query.atoms]
    return found.select("rank", "weight", *[F.col(f"rid_{held.index(x) + 1}{path}").alias(f"rid_{n + 1}") for n, (x, path) in enumerate(places[m] for m in names)])


def _inside(query: Query, a: str, b: str) -> list[P.Condition]:
    return [c for c in query.conjuncts() if covered(c) == {a, b}]


def _bagged(query: Query, a: str, b: str, bag: str) -> Query | None:
    """The query with one atom for two; its relation is still missing. None if nothing joins the two, or nothing else."""
    outside = [c for c in query.conjuncts() if covered(c) != {a, b}]
    if not _inside(query, a, b) or not outside:
        return None

    def moved(c):
        if isinstance(c, P.Compare):
            to = lambda s: P.Side(bag, f"{s.alias}_{ranked.key_name(s)}") if s.alias in (a, b) else s
            return P.Compare(c.op, to(c.left), to(c.right), c.eps)
        if isinstance(c, P.Negated):
            return P.Negated(moved(c.a))
        return type(c)(moved(c.a), moved(c.b))

    atoms = [Atom(bag, x.df) if x.alias == a else x for x in query.atoms if x.alias != b]
    return replace(query, atoms=atoms, where=P.all_of(*[moved(c) for c in outside]))


def _filled(query: Query, a: str, b: str, made: Query, bag: str, method: str) -> Query:
    """``made`` with the bag's rows: the pairs of a and b with their weights and the keys that other atoms ask for."""
    frames = {x: query.atom(x).df.where(query.atom(x).where) if query.atom(x).where else query.atom(x).df for x in (a, b)}
    pairs = theta_join(frames[a], frames[b], _renamed(P.all_of(*_inside(query, a, b)), {a: "s", b: "t"}), method, query.atom(a).rid, query.atom(b).rid)
    asked = [s for c in query.conjuncts() if covered(c) != {a, b} for t in P.to_dnf(c) for p in t for s in (p.left, p.right)]
    for x, rid in ((a, "rid_s"), (b, "rid_t")):
        atom = query.atom(x)
        keys = [F.expr(s.expr).alias(f"{x}_{ranked.key_name(s)}") for s in dict.fromkeys(s for s in asked if s.alias == x)]
        pairs = pairs.join(frames[x].select(F.expr(atom.rid).alias(rid), F.expr(atom.weight).alias(f"w_{rid}"), *keys), rid)
    weight = {"product": "w_rid_s * w_rid_t", "bottleneck": f"{'least' if query.rank.desc else 'greatest'}(w_rid_s, w_rid_t)"}.get(query.rank.name, "w_rid_s + w_rid_t")
    staged = Staging(frames[a].sparkSession, "bag").save(pairs, bag)
    atom = Atom(bag, staged, "struct(rid_s AS a, rid_t AS b)", weight)
    return replace(made, atoms=[atom if x.alias == bag else x for x in made.atoms])
