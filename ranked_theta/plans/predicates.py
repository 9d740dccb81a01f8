"""Join conditions: comparisons of expressions on two atoms, under AND, OR and NOT.

A side is ``(alias, expression)`` or the text ``"alias.column"``; the expression is SQL
over the columns of that atom. ``to_dnf`` turns a condition into terms of comparisons;
negations are pushed into the comparisons, so that a term holds nothing but atoms of
``<  <=  >  >=  =  !=  band`` and opaque ones.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

FLIP = {"<": ">", "<=": ">=", ">": "<", ">=": "<=", "=": "=", "!=": "!=", "band": "band"}
NEGATE = {"<": ">=", "<=": ">", ">": "<=", ">=": "<", "=": "!=", "!=": "="}
#: Terms that a condition may have; conversion can grow exponentially with the query.
MOST_TERMS = 64


class Condition:
    def __and__(self, other: Condition) -> Condition:
        return Both(self, other)

    def __or__(self, other: Condition) -> Condition:
        return Either(self, other)

    def __invert__(self) -> Condition:
        return Negated(self)


@dataclass(frozen=True)
class Side:
    alias: str
    expr: str


def side(x) -> Side:
    if isinstance(x, Side):
        return x
    if isinstance(x, tuple):
        return Side(*x)
    alias, _, column = x.partition(".")
    return Side(alias, column)


@dataclass(frozen=True)
class Compare(Condition):
    op: str
    left: Side
    right: Side
    eps: int | None = None

    @property
    def atoms(self) -> frozenset[str]:
        return frozenset((self.left.alias, self.right.alias))

    def seen_from(self, alias: str) -> Compare:
        """The same comparison with ``alias`` on the left."""
        return self if self.left.alias == alias else Compare(FLIP[self.op], self.right, self.left, self.eps)


@dataclass(frozen=True)
class Opaque(Condition):
    """A predicate on two atoms as a SQL text in which columns are written alias.column."""

    aliases: tuple[str, str]
    text: str
    negated: bool = False

    @property
    def atoms(self) -> frozenset[str]:
        return frozenset(self.aliases)

    def sides(self) -> list[Side]:
        """The columns that the text names, by atom."""
        return [Side(alias, c) for alias in self.aliases for c in dict.fromkeys(re.findall(rf"\b{re.escape(alias)}\.([A-Za-z_]\w*)", self.text))]

    def over(self, name) -> str:
        """The text with each column as ``name(side)`` says."""
        text = re.sub(rf"\b({'|'.join(map(re.escape, self.aliases))})\.([A-Za-z_]\w*)", lambda m: name(Side(m[1], m[2])), self.text)
        return f"NOT ({text})" if self.negated else f"({text})"


@dataclass(frozen=True)
class Both(Condition):
    a: Condition
    b: Condition


@dataclass(frozen=True)
class Either(Condition):
    a: Condition
    b: Condition


@dataclass(frozen=True)
class Negated(Condition):
    a: Condition


def _make(op):
    return lambda a, b: Compare(op, side(a), side(b))


lt, le, gt, ge, eq, ne = (_make(op) for op in ("<", "<=", ">", ">=", "=", "!="))


def band(a, b, eps: int) -> Compare:
    """|a - b| < eps on exact numbers."""
    if eps <= 0:
        raise ValueError("a band needs a positive width")
    return Compare("band", side(a), side(b), eps)


def opaque(a: str, b: str, text: str) -> Opaque:
    return Opaque((a, b), text)


def const(alias: str, value) -> Side:
    """A constant as the other side of a comparison with an expression of the atom ``alias``."""
    return Side(alias, f"'{value}'" if isinstance(value, str) else str(value))


def all_of(*conditions: Condition) -> Condition:
    return reduce(Both, conditions)


def any_of(*conditions: Condition) -> Condition:
    return reduce(Either, conditions)


def shifted(s: Side, by: int) -> Side:
    return Side(s.alias, f"({s.expr}) + {by}L" if by >= 0 else f"({s.expr}) - {-by}L")


def to_dnf(c: Condition, negated: bool = False) -> list[list[Compare | Opaque]]:
    """Terms of a condition."""
    if isinstance(c, Negated):
        return to_dnf(c.a, not negated)
    if isinstance(c, (Both, Either)):
        a, b = to_dnf(c.a, negated), to_dnf(c.b, negated)
        if isinstance(c, Either) != negated:
            return a + b
        if len(a) * len(b) > MOST_TERMS:
            raise ValueError(f"the condition has over {MOST_TERMS} terms")
        return [list(dict.fromkeys(x + y)) for x in a for y in b]
    if not negated:
        return [[c]]
    if isinstance(c, Opaque):
        return [[Opaque(c.aliases, c.text, not c.negated)]]
    if c.op == "band":  # two sides of a band exclude each other
        return [[Compare(">=", c.right, shifted(c.left, c.eps))], [Compare("<=", c.right, shifted(c.left, -c.eps))]]
    return [[Compare(NEGATE[c.op], c.left, c.right)]]


def factor(terms: list[list]) -> tuple[list, list[list]]:
    """Comparisons that all terms share, and what is left of each term."""
    shared = [p for p in terms[0] if all(p in t for t in terms)]
    return shared, [[p for p in t if p not in shared] for t in terms]


def one_sided(c: Condition) -> str:
    """SQL over an atom's own columns for a condition on that atom alone."""

    def text(p: Compare | Opaque) -> str:
        if isinstance(p, Opaque):
            return f"{'NOT ' if p.negated else ''}({p.text.replace(p.aliases[0] + '.', '')})"
        if p.op == "band":
            return f"abs(({p.left.expr}) - ({p.right.expr})) < {p.eps}"
        return f"({p.left.expr}) {'<>' if p.op == '!=' else p.op} ({p.right.expr})"

    return " OR ".join("(" + " AND ".join(text(p) for p in term) + ")" for term in to_dnf(c))


def to_column(p: Compare, left: Column, right: Column) -> Column:
    """A comparison on two columns."""
    if p.op == "band":
        return F.abs(left - right) < F.lit(p.eps)
    return {"<": left < right, "<=": left <= right, ">": left > right, ">=": left >= right, "=": left == right, "!=": left != right}[p.op]
