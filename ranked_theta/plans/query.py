"""Queries: atoms, a join condition, a ranking and a head."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import predicates as P


@dataclass(frozen=True)
class Atom:
    """A relation under an alias.

    ``rid``: SQL of a value that is unique per row (a struct if need be); ``weight``: SQL
    of an exact number; ``lex``: SQL of the attribute for lexicographic ranking. Rows whose
    weight is null are dropped.
    """

    alias: str
    df: DataFrame
    rid: str = "rid"
    weight: str = "w"
    where: str | None = None
    lex: str | None = None


@dataclass(frozen=True)
class Rank:
    """How weights combine, as an order in which less is better.

    Internally every weight is ``lift``ed so that the best answer has the least value,
    and ``shown`` brings it back.
    """

    name: str
    desc: bool = False
    #: Whether a better part always makes a better whole; the tie-break by ids needs it.
    strict: bool = True

    @staticmethod
    def sum(desc: bool = False) -> Rank:
        return Rank("sum", desc)

    @staticmethod
    def product() -> Rank:
        """Greatest product of positive whole weights, in DECIMAL(38,0)."""
        return Rank("product", True)

    @staticmethod
    def bottleneck(desc: bool = False) -> Rank:
        """Least largest weight; with ``desc`` the greatest smallest one."""
        return Rank("bottleneck", desc, False)

    @staticmethod
    def lex() -> Rank:
        """By the first atom's ``lex`` attribute, then the second's, and so on."""
        return Rank("lex")

    def lift(self, w: Column) -> Column:
        if self.name == "product":
            return -w.cast("decimal(38,0)")
        if self.name == "lex":
            return F.lit(0).cast("long")
        return -w if self.desc else w

    def combine(self, parts: list[Column]) -> Column:
        if self.name == "product":
            return reduce(lambda a, b: (-(a * b)).cast("decimal(38,0)"), parts)
        if self.name == "bottleneck":
            return F.greatest(*parts) if len(parts) > 1 else parts[0]
        return reduce(lambda a, b: a + b, parts)

    def shown(self, w: Column) -> Column:
        return -w if self.desc else w


@dataclass(frozen=True)
class Query:
    """Atoms joined by ``where`` (a condition on pairs of atoms), ranked by ``rank``."""

    atoms: list[Atom]
    where: P.Condition
    rank: Rank = field(default_factory=Rank.sum)

    def __post_init__(self):
        names = [a.alias for a in self.atoms]
        if len(set(names)) != len(names):
            raise ValueError("aliases repeat")
        for p in self.predicates():
            if not p.atoms <= set(names):
                raise ValueError(f"{p} names an unknown atom")

    def conjuncts(self) -> list[P.Condition]:
        """The top-level conjuncts of the condition."""
        out, todo = [], [self.where]
        while todo:
            c = todo.pop(0)
            if isinstance(c, P.Both):
                todo = [c.a, c.b, *todo]
            else:
                out.append(c)
        return out

    def routed(self) -> Query:
        """The query with conjuncts on one atom moved into that atom's selection."""
        kept, filters = [], {}
        for c in self.conjuncts():
            atoms = frozenset().union(*(p.atoms for t in P.to_dnf(c) for p in t))
            if len(atoms) == 1:
                filters.setdefault(*atoms, []).append(P.one_sided(c))
            else:
                kept.append(c)
        if not filters:
            return self
        if not kept:
            raise ValueError("the condition joins nothing")
        put = lambda a: replace(a, where=" AND ".join(f"({x})" for x in ([a.where] if a.where else []) + filters[a.alias]))
        return replace(self, atoms=[put(a) if a.alias in filters else a for a in self.atoms], where=P.all_of(*kept))

    def predicates(self) -> list:
        return [p for term in P.to_dnf(self.where) for p in term]

    def atom(self, alias: str) -> Atom:
        return next(a for a in self.atoms if a.alias == alias)

    def index(self, alias: str) -> int:
        return [a.alias for a in self.atoms].index(alias)
