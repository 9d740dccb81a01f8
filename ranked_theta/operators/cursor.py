"""Ranked cursor: pages of answers, as many as the reader asks for."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import predicates as P
from ..plans.query import Query
from .ranked import Passes, _passes


class RankedCursor:
    """Answers of an acyclic query in order.

    The bottom-up pass runs once. The first request cuts the atoms for its k; when a
    reader goes on beyond it, k doubles, so that the work done again is a constant factor.
    """

    def __init__(self, query: Query, first: int = 1000, root: str | None = None):
        self.query, self.k, self.at = query, first, 0
        self.passes: Passes = _passes(query, root)
        self._found: list[Row] | None = None
        self._whole = False

    def _fill(self, upto: int) -> None:
        while not self._whole and (self._found is None or len(self._found) < upto):
            while self.k < upto:
                self.k *= 2
            self.passes.cut(self.k)
            self._found = self.passes.answers(self.passes.beam(self.k), self.k).orderBy("rank").collect()  # k rows
            self._whole = len(self._found) < self.k
            if not self._whole and len(self._found) < upto:
                self.k *= 2

    def next(self, m: int = 1) -> list[Row]:
        """The next m answers; fewer at the end."""
        self._fill(self.at + m)
        page = self._found[self.at : self.at + m]
        self.at += len(page)
        return page

    def top(self, k: int) -> list[Row]:
        self._fill(k)
        return self._found[:k]

    def since(self, rank: int, m: int) -> list[Row]:
        """m answers after the one of this rank."""
        self._fill(rank + m)
        return self._found[rank : rank + m]

    def __iter__(self) -> Iterator[Row]:
        while page := self.next(1):
            yield page[0]


def per_group(query: Query, key: str, k: int) -> DataFrame:
    """The k best answers for each value of an equality key that all atoms share (column ``key`` of each).

    All groups go through the same passes: the key is an equality on every edge, each atom
    keeps its k best rows of every group, and prefixes are cut to k per group. So no task
    and no table holds more than k rows of a group, however many groups there are.
    """
    names = [a.alias for a in query.atoms]
    shared = P.all_of(*[P.eq(f"{names[0]}.{key}", f"{n}.{key}") for n in names[1:]], query.where)
    passes = _passes(Query(query.atoms, shared, query.rank), None)
    return GroupPasses(passes, key).top_k(k)


class GroupPasses:
    """The passes of a query with cuts per group."""

    def __init__(self, passes: Passes, key: str):
        from .ranked import key_name

        self.passes, self.key = passes, key_name(P.side(f"x.{key}"))

    def _first(self, rows: DataFrame, order: str, group: str, k: int) -> DataFrame:
        place = F.row_number().over(Window.partitionBy(group).orderBy(order))
        return rows.withColumn("_place", place).where(F.col("_place") <= k).drop("_place")

    def top_k(self, k: int) -> DataFrame:
        """group_key, rank, weight, rid_1..: at most k answers for each group."""
        from . import fold as folds
        from .ranked import edge_terms, flipped

        p = self.passes
        tree, everyone = p.tree, range(len(p.query.atoms))
        p.reduced[tree.root] = p.staging.save(self._first(p.bottom_up(), "pi", self.key, k), "group-root")
        outside = {tree.root: None}
        for alias in tree.preorder():
            for child in tree.children[alias]:
                rest = [(tree.subtree(c), F.col(f"m_{c}")) for c in tree.children[alias] if c != child]
                if outside[alias] is not None:
                    rest.append((sorted(set(everyone) - set(tree.subtree(alias))), F.col("up")))
                given = p.reduced[alias].withColumn("val", p.value([p.own(alias)], rest))
                kept = folds.fold(p.up[child], given, flipped(edge_terms(tree, alias, child)), "min", "up", p.staging, f"group-{child}", p.sizer(child, alias), None, p.known)
                inside = tree.subtree(child)
                through = p.value([], [(inside, F.col("pi")), (sorted(set(everyone) - set(inside)), F.col("up"))])
                p.reduced[child] = p.staging.save(self._first(kept.withColumn("thru", through), "thru", self.key, k).drop("thru"), f"group-{child}")
                outside[child] = F.col("up")
        order = tree.preorder()
        group = f"{self.key}_{p.query.index(order[0])}"
        prefix, done = p._table(order[0]), [order[0]]
        for alias in order[1:]:
            prefix = p._condition_step(prefix, done, alias, k)
            done.append(alias)
            pending = [c for a in done for c in tree.children[a] if c not in done]
            prefix = prefix.withColumn("total", p.value([p._single(a) for a in done], [(tree.subtree(c), F.col(f"m_{c}")) for c in pending]))
            prefix = self._first(prefix, "total", group, k)
            if alias != order[-1]:
                prefix = p.staging.save(prefix.drop("total"), f"group-beam-{alias}")
        place = F.row_number().over(Window.partitionBy(group).orderBy("total")).cast("long")
        out = prefix.select(F.col(group).alias("group_key"), place.alias("rank"), p.query.rank.shown(F.col("total.w")).alias("weight"), *[F.col(f"total.r{i}").alias(f"rid_{i + 1}") for i in everyone])
        return p.name_rows(out, {f"rid_{i + 1}": p.query.atoms[i].alias for i in everyone})
