"""The experiment workloads on the given tables: queries and their plain-join oracles."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.predicates import Condition, all_of, any_of, band, eq, gt, lt, ne
from ..plans.query import Atom, Query, Rank
from . import views


@dataclass(frozen=True)
class Workload:
    """``view(spark, dir)`` and ``view_sql`` give the relation; ``wheres`` one filter per atom."""

    view: Callable[[SparkSession, str], DataFrame]
    view_sql: str
    wheres: tuple[str | None, ...]
    weight: str
    rank: Rank
    step: Callable[[str, str], Condition]
    step_sql: str
    rid_text: bool = False
    close: tuple[Callable[[str, str], Condition], str] | None = None

    @property
    def length(self) -> int:
        return len(self.wheres)

    def query(self, spark: SparkSession, sf_dir: str) -> Query:
        base = self.view(spark, sf_dir)
        names = [f"t{i + 1}" for i in range(self.length)]
        atoms = [Atom(n, base, weight=self.weight, where=w) for n, w in zip(names, self.wheres, strict=True)]
        conditions = [self.step(a, b) for a, b in zip(names, names[1:], strict=False)]
        if self.close:
            conditions.append(self.close[0](names[-1], names[0]))
        return Query(atoms, all_of(*conditions), self.rank)

    def _atoms_sql(self) -> list[str]:
        return [f"(SELECT * FROM v{' WHERE ' + w if w else ''})" for w in self.wheres]

    def _joined_sql(self) -> tuple[str, str]:
        names = [f"t{i + 1}" for i in range(self.length)]
        tables = ", ".join(f"{x} {n}" for x, n in zip(self._atoms_sql(), names, strict=True))
        on = [f"({self.step_sql.format(l=a, r=b)})" for a, b in zip(names, names[1:], strict=False)]
        if self.close:
            on.append(f"({self.close[1].format(l=names[-1], r=names[0])})")
        return f"WITH v AS ({self.view_sql})", f"FROM {tables} WHERE {' AND '.join(on)}"

    def _numbered_sql(self) -> str:
        """The relation with a row number, written once."""
        return f"WITH v AS MATERIALIZED (SELECT *, row_number() OVER () AS q FROM ({self.view_sql}))"

    def _stepwise_sql(self, k: int) -> str:
        """Best completions by pairs of neighbours, and a chain of joins that leaves out what is behind the k-th answer."""
        n, atoms = self.length, self._atoms_sql()
        w = f"{'-' if self.rank.desc else ''}{self.weight}"
        on = lambda l, r: self.step_sql.format(l=l, r=r)
        out = [self._numbered_sql(), f"g{n} AS MATERIALIZED (SELECT *, {w} AS best FROM {atoms[-1]})"]
        for i in range(n - 1, 0, -1):
            out.append(f"g{i} AS MATERIALIZED (SELECT l.*, {w} + m.least AS best FROM {atoms[i - 1]} l JOIN (SELECT l.q, min(r.best) AS least FROM {atoms[i - 1]} l JOIN g{i + 1} r ON {on('l', 'r')} GROUP BY l.q) m USING (q))")
        # different prefixes lie in different answers, so that the k best of them bound the k-th
        rid = "rid_text" if self.rid_text else "rid"
        tau = lambda i: f"tau{i} AS MATERIALIZED (SELECT CASE WHEN count(*) < {k} THEN NULL ELSE max(total) END AS most FROM (SELECT total FROM p{i} ORDER BY total LIMIT {k}))"
        out += [f"p1 AS MATERIALIZED (SELECT * EXCLUDE (best), {w} AS acc, best AS total, rid AS o1, {rid} AS rid_1 FROM g1)", tau(1)]
        for i in range(2, n + 1):
            ids = ", ".join(f"l.o{j}, l.rid_{j}" for j in range(1, i))
            out.append(f"p{i} AS MATERIALIZED (SELECT r.* EXCLUDE (best), l.acc + ({w.replace(self.weight, 'r.' + self.weight)}) AS acc, l.acc + r.best AS total, {ids}, r.rid AS o{i}, r.{rid} AS rid_{i} FROM p{i - 1} l JOIN g{i} r ON {on('l', 'r')}, tau{i - 1} tau WHERE tau.most IS NULL OR l.acc + r.best <= tau.most)")
            out.append(tau(i))
        order = "acc, " + ", ".join(f"o{i + 1}" for i in range(n))
        shown = ", ".join(f"rid_{i + 1}" for i in range(n))
        return f"{', '.join(out)} SELECT row_number() OVER (ORDER BY {order}) AS rank, CAST({'-' if self.rank.desc else ''}acc AS BIGINT) AS weight, {shown} FROM p{n} ORDER BY {order} LIMIT {k}"

    def oracle(self, k: int) -> str:
        """DuckDB for the k best answers: the plain join of two atoms, or stepwise for more."""
        if self.length > 2 and self.rank.name == "sum" and not self.close:
            return self._stepwise_sql(k)
        names = [f"t{i + 1}" for i in range(self.length)]
        head, rest = self._joined_sql()
        weights = [f"{n}.{self.weight}" for n in names]
        if self.rank.name == "product":
            total = " * ".join(f"CAST({w} AS HUGEINT)" for w in weights)
        elif self.rank.name == "bottleneck":
            total = f"{'least' if self.rank.desc else 'greatest'}({', '.join(weights)})"
        else:
            total = " + ".join(weights)
        order = f"weight {'DESC' if self.rank.desc else 'ASC'}, " + ", ".join(f"o{i + 1}" for i in range(self.length))
        ids = ", ".join(f"{n}.rid AS o{i + 1}, {n}.{'rid_text' if self.rid_text else 'rid'} AS rid_{i + 1}" for i, n in enumerate(names))
        shown = "CAST(weight AS DECIMAL(38,0))" if self.rank.name == "product" else "CAST(weight AS BIGINT)"
        out = ", ".join(f"rid_{i + 1}" for i in range(self.length))
        return f"{head} SELECT row_number() OVER (ORDER BY {order}) AS rank, {shown} AS weight, {out} FROM (SELECT {total} AS weight, {ids} {rest} ORDER BY {order} LIMIT {k})"

    def count_sql(self) -> str:
        """DuckDB for the size of the join: counted along pairs of neighbours."""
        if self.close:
            head, rest = self._joined_sql()
            return f"{head} SELECT count(*)::BIGINT AS answers {rest}"
        n, atoms = self.length, self._atoms_sql()
        out = [self._numbered_sql(), f"c{n} AS MATERIALIZED (SELECT *, 1::HUGEINT AS n FROM {atoms[-1]})"]
        for i in range(n - 1, 0, -1):
            out.append(f"c{i} AS MATERIALIZED (SELECT l.*, m.n FROM {atoms[i - 1]} l JOIN (SELECT l.q, sum(r.n)::HUGEINT AS n FROM {atoms[i - 1]} l JOIN c{i + 1} r ON {self.step_sql.format(l='l', r='r')} GROUP BY l.q) m USING (q))")
        return f"{', '.join(out)} SELECT coalesce(sum(n), 0)::BIGINT AS answers FROM c1"

    def readable(self, found: DataFrame) -> DataFrame:
        """Struct ids as text, for comparison with other engines."""
        if not self.rid_text:
            return found
        return found.withColumns({f"rid_{i + 1}": F.concat_ws("|", *[F.col(f"rid_{i + 1}.{f.name}").cast("string") for f in found.schema[f"rid_{i + 1}"].dataType.fields]) for i in range(self.length)})


def chain_inequality(length: int, source: str = "orders", domain: int = 10_000, rank: Rank | None = None) -> Workload:
    """Synthetic single inequality: left.b < right.a."""
    return Workload(lambda s, d: views.slices(s, d, source, domain), views.slices_sql(source, domain), (None,) * length, "w", rank or Rank.sum(), lambda a, b: lt(f"{a}.b", f"{b}.a"), "{l}.b < {r}.a")


def chain_band(length: int, source: str = "orders") -> Workload:
    """Synthetic band and non-equality."""
    return Workload(lambda s, d: views.slices(s, d, source), views.slices_sql(source), (None,) * length, "w", Rank.sum(), lambda a, b: band(f"{a}.b", f"{b}.a", 50) & ne(f"{a}.a", f"{b}.b"), "abs({l}.b - {r}.a) < 50 AND {l}.a <> {r}.b")


def sales_rise(length: int, where: str | None = None) -> Workload:
    """Sales of one supplier with rising quantity and ship date."""
    return Workload(views.sales, views.sales_sql(), (where,) * length, "w", Rank.sum(), lambda a, b: all_of(eq(f"{a}.supp", f"{b}.supp"), lt(f"{a}.qty", f"{b}.qty"), lt(f"{a}.ship", f"{b}.ship")), "{l}.supp = {r}.supp AND {l}.qty < {r}.qty AND {l}.ship < {r}.ship", True)


def sales_any_date(length: int, where: str | None = None) -> Workload:
    """As ``sales_rise``, with any of three dates rising."""
    dates = ("ship", "commit_", "receipt")
    return Workload(views.sales, views.sales_sql(), (where,) * length, "w", Rank.sum(), lambda a, b: all_of(eq(f"{a}.supp", f"{b}.supp"), lt(f"{a}.qty", f"{b}.qty"), any_of(*[lt(f"{a}.{d}", f"{b}.{d}") for d in dates])), "{l}.supp = {r}.supp AND {l}.qty < {r}.qty AND (" + " OR ".join(f"{{l}}.{d} < {{r}}.{d}" for d in dates) + ")", True)


def temporal_paths(length: int) -> Workload:
    """Paths along rising time, least total sentiment."""
    return Workload(views.edges, views.edges_sql(), (None,) * length, "s", Rank.sum(), lambda a, b: eq(f"{a}.dst", f"{b}.src") & lt(f"{a}.ts", f"{b}.ts"), "{l}.dst = {r}.src AND {l}.ts < {r}.ts")


def falling_paths(length: int) -> Workload:
    """As ``temporal_paths`` with falling sentiment, greatest total readability."""
    return Workload(views.edges, views.edges_sql(), (None,) * length, "r", Rank.sum(desc=True), lambda a, b: all_of(eq(f"{a}.dst", f"{b}.src"), lt(f"{a}.ts", f"{b}.ts"), gt(f"{a}.s", f"{b}.s")), "{l}.dst = {r}.src AND {l}.ts < {r}.ts AND {l}.s > {r}.s")


def near_places(eps: int = 10_000) -> Workload:
    """Spatial band join, greatest total weight."""
    return Workload(views.places, views.places_sql(), (None, None), "w", Rank.sum(desc=True), lambda a, b: band(f"{a}.x", f"{b}.x", eps) & band(f"{a}.y", f"{b}.y", eps), f"abs({{l}}.x - {{r}}.x) < {eps} AND abs({{l}}.y - {{r}}.y) < {eps}")


def near_points(eps_x: int = 3_600_000_000, eps_y: int = 500) -> Workload:
    """Time and value bands on events."""
    return Workload(views.points, views.points_sql(), (None, None), "w", Rank.sum(desc=True), lambda a, b: band(f"{a}.x", f"{b}.x", eps_x) & band(f"{a}.y", f"{b}.y", eps_y), f"abs({{l}}.x - {{r}}.x) < {eps_x} AND abs({{l}}.y - {{r}}.y) < {eps_y}")


def likely_paths(length: int) -> Workload:
    """Paths along rising time, greatest product of probabilities."""
    return Workload(views.edges, views.edges_sql(), ("prob is not null",) * length, "prob", Rank.product(), lambda a, b: eq(f"{a}.dst", f"{b}.src") & lt(f"{a}.ts", f"{b}.ts"), "{l}.dst = {r}.src AND {l}.ts < {r}.ts")


#: The tables of the triangle's atoms.
TRIANGLE = ("supplier", "customer", "supplier")


def triangle(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = TRIANGLE) -> Query:
    """A cycle of inequalities over whole tables, one for each atom."""
    names = [f"t{i + 1}" for i in range(len(sources))]
    frames = {x: views.slices(spark, sf_dir, x) for x in set(sources)}
    where = all_of(*[lt(f"{a}.b", f"{b}.a") for a, b in zip(names, [*names[1:], names[0]], strict=True)])
    return Query([Atom(n, frames[x]) for n, x in zip(names, sources, strict=True)], where)


def triangle_sql(k: int | None = None, sources: tuple[str, ...] = TRIANGLE) -> str:
    """Its size, or its k best answers."""
    names = [f"t{i + 1}" for i in range(len(sources))]
    tables = ", ".join(f"({views.slices_sql(x)}) {n}" for n, x in zip(names, sources, strict=True))
    on = " AND ".join(f"{a}.b < {b}.a" for a, b in zip(names, [*names[1:], names[0]], strict=True))
    if k is None:
        return f"SELECT count(*)::BIGINT AS answers FROM {tables} WHERE {on}"
    ids = ", ".join(f"{n}.rid AS rid_{i + 1}" for i, n in enumerate(names))
    order = ", ".join(f"rid_{i + 1}" for i in range(len(names)))
    return f"SELECT row_number() OVER (ORDER BY weight, {order}) AS rank, * FROM (SELECT ({' + '.join(f'{n}.w' for n in names)})::BIGINT AS weight, {ids} FROM {tables} WHERE {on} ORDER BY 1, {order} LIMIT {k})"
