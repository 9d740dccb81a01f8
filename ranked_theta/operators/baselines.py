"""The methods that the factorised engine is compared with."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import predicates as P
from ..plans.jointree import plan_tree
from ..plans.query import Atom, Query
from ..sources.staging import Staging
from . import connectors, ranked
from . import fold as folds

#: Tasks that the rows of a cell are dealt over in ``native_sql``.
DEALT = 4


def _frames(query: Query) -> dict[str, DataFrame]:
    return {a.alias: (a.df.where(a.where) if a.where else a.df) for a in query.atoms}


def plain_join(query: Query) -> DataFrame:
    """rid_1.., weight of all answers by Spark's own joins on the condition as it stands."""
    out, names = None, [a.alias for a in query.atoms]
    sides: dict[str, list] = {n: [] for n in names}
    for p in query.predicates():
        for s in (p.left, p.right):
            sides[s.alias].append(s)
    frames, seen = _frames(query), []
    for atom in query.atoms:
        cols = [F.expr(s.expr).alias(f"{atom.alias}_{ranked.key_name(s)}") for s in dict.fromkeys(sides[atom.alias])]
        rows = frames[atom.alias].select(F.expr(atom.rid).alias(f"rid_{atom.alias}"), query.rank.lift(F.expr(atom.weight)).alias(f"w_{atom.alias}"), *cols)
        seen.append(atom.alias)
        if out is None:
            out = rows
            continue
        cond = F.lit(True)
        for c in query.conjuncts():
            atoms = frozenset().union(*(p.atoms for t in P.to_dnf(c) for p in t))
            if atom.alias in atoms and atoms <= set(seen):
                either = None
                for term in P.to_dnf(c):
                    both = None
                    for p in term:
                        one = P.to_column(p, F.col(f"{p.left.alias}_{ranked.key_name(p.left)}"), F.col(f"{p.right.alias}_{ranked.key_name(p.right)}"))
                        both = one if both is None else both & one
                    either = both if either is None else either | both
                cond = cond & either
        out = out.join(rows, cond)
    return out.select(query.rank.combine([F.col(f"w_{n}") for n in names]).alias("w"), *[F.col(f"rid_{n}").alias(f"rid_{i + 1}") for i, n in enumerate(names)])


def materialize_rank(query: Query, k: int, how: str = "heap", output: DataFrame | None = None) -> DataFrame:
    """Join first, then rank: a heap of k, or a sort of everything, which is written in full before the first row is read.

    ``output``: the join's result (see ``prepared_output``), which is then not charged.
    """
    rows = plain_join(query) if output is None else output
    ids = [c for c in rows.columns if c != "w"]
    if how == "sort":
        n = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
        rows = Staging(rows.sparkSession, "sort").save(rows.repartitionByRange(n, "w", *ids).sortWithinPartitions("w", *ids), "sorted")
    ordered = rows.orderBy("w", *ids).limit(k)
    return ordered.select(F.row_number().over(Window.orderBy("w", *ids)).cast("long").alias("rank"), query.rank.shown(F.col("w")).alias("weight"), *ids)


def prepared_output(query: Query) -> DataFrame:
    """The join's result as a written table, for an idealised baseline that only ranks it."""
    return Staging(query.atoms[0].df.sparkSession, "output").save(plain_join(query), "output")


def local_heap(rows: list[tuple], k: int) -> list[tuple]:
    """The idealised in-memory ranking of a given output."""
    heap = list(rows)
    heapq.heapify(heap)
    return [heapq.heappop(heap) for _ in range(min(k, len(heap)))]


def direct_equi(query: Query, k: int, edges: dict | None = None) -> DataFrame:
    """Ranked enumeration over an equi-join whose edge relations list all joining pairs.

    ``edges``: pairs (rid_s, rid_t, pid) by tree edge, computed beforehand and not charged.
    """
    tree = plan_tree(query)
    edges = edges if edges is not None else direct_edges(query)
    atoms, conditions, names = [], [], {}
    for alias in tree.preorder():
        parent = tree.parent(alias)
        atom = query.atom(alias)
        if parent is not None:
            pair = f"{parent}_{alias}"
            atoms.append(Atom(pair, edges[parent, alias], "pid", "CAST(0 AS BIGINT)" if query.rank.name == "sum" else "CAST(1 AS BIGINT)"))
            conditions += [P.eq((parent, query.atom(parent).rid), (pair, "rid_s")), P.eq((pair, "rid_t"), (alias, atom.rid))]
        atoms.append(atom)
    made = Query(atoms, P.all_of(*conditions), query.rank)
    found = ranked.top_k(made, k, root=tree.root)
    for i, a in enumerate(atoms):
        names[a.alias] = f"rid_{i + 1}"
    return found.select("rank", "weight", *[F.col(names[a.alias]).alias(f"rid_{i + 1}") for i, a in enumerate(query.atoms)])


def direct_edges(query: Query) -> dict[tuple[str, str], DataFrame]:
    """All joining pairs of every tree edge, written, with numbers in the order of their ids."""
    tree = plan_tree(query)
    query, staging = tree.query, Staging(query.atoms[0].df.sparkSession, "pairs")
    passes = ranked.Passes(query, tree, None)
    out = {}
    for parent, child in tree.conditions:
        left, right = (ranked.prepare(query, a, passes.sides(a)).drop("w") for a in (parent, child))
        pairs = connectors.build(left, right, ranked.edge_terms(tree, parent, child), "direct").parts[0]
        out[parent, child] = folds.placed(pairs.withColumn("pair", F.struct("rid_s", "rid_t")), "pair", "pid", staging, f"{parent}-{child}").drop("pair")
    return out


def native_sql(query: Query, k: int, cached: bool = False) -> DataFrame:
    """The same question as SQL text with ORDER BY and LIMIT, planned by Spark alone.

    Where two atoms have no equality but a band of whole numbers, the text says that their
    cells are equal or neighbours, which Spark doesn't derive and without which it compares
    all pairs. ``cached`` keeps the relations in memory while it runs.
    """
    spark = query.atoms[0].df.sparkSession
    frames = _frames(query)
    for atom in query.atoms:
        rows = frames[atom.alias].select("*", F.expr(atom.rid).alias("rid__"), F.expr(atom.weight).alias("w__"))
        rows.createOrReplaceTempView(f"native_{atom.alias}")
        if cached:
            spark.catalog.cacheTable(f"native_{atom.alias}")
    total = {"product": " * ", "sum": " + "}[query.rank.name].join(f"CAST({a.alias}.w__ AS DECIMAL(38,0))" if query.rank.name == "product" else f"{a.alias}.w__" for a in query.atoms)
    ids = [f"{a.alias}.rid__ AS rid_{i + 1}" for i, a in enumerate(query.atoms)]
    order = f"weight {'DESC' if query.rank.desc else 'ASC'}, " + ", ".join(f"rid_{i + 1}" for i in range(len(ids)))
    shared, rest = P.factor(P.to_dnf(query.where))
    where = " AND ".join([_text(p) for p in shared] + (["(" + " OR ".join("(" + (" AND ".join(_text(p) for p in t) or "TRUE") + ")" for t in rest) + ")"] if any(rest) else []))
    tables, hint = {a.alias: f"native_{a.alias}" for a in query.atoms}, ""
    band = next((p for p in shared if p.op == "band" and p.left.alias != p.right.alias), None)
    if band is not None and len(query.atoms) == 2 and all(p.op != "=" for p in shared) and _whole(band, frames):
        tables, hint = _by_cells(band, spark), f"/*+ MERGE({band.left.alias}, {band.right.alias}) */ "
        where += f" AND {band.left.alias}.cell__ = {band.right.alias}.cell__ AND {band.left.alias}.deal__ = {band.right.alias}.deal__"
    sql = f"SELECT {hint}{total} AS weight, {', '.join(ids)} FROM {', '.join(f'{tables[a.alias]} {a.alias}' for a in query.atoms)} WHERE {where} ORDER BY {order} LIMIT {k}"
    found = spark.sql(sql)
    w = Window.orderBy(F.col("weight").desc() if query.rank.desc else F.col("weight"), *[f"rid_{i + 1}" for i in range(len(ids))])
    out = found.select(F.row_number().over(w).cast("long").alias("rank"), *found.columns)
    if cached:
        out = Staging(spark, "native").save(out, "answers")
        for atom in query.atoms:
            spark.catalog.uncacheTable(f"native_{atom.alias}")
    return out


def _whole(band: P.Compare, frames: dict[str, DataFrame]) -> bool:
    """Whether a band has cells: whole numbers on both sides and a whole width."""
    kinds = [frames[x.alias].select(F.expr(x.expr)).dtypes[0][1] for x in (band.left, band.right)]
    return isinstance(band.eps, int) and band.eps > 0 and all(k in ("bigint", "int", "smallint", "tinyint") for k in kinds)


def _by_cells(band: P.Compare, spark: SparkSession) -> dict[str, str]:
    """Both relations with cells as wide as the band: each left row in its own and both next ones, so that a pair meets once.

    Rows of a cell are dealt over DEALT tasks; the pairs are many more than the rows, so that the number of tasks is said.
    """
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    cell = lambda e: f"CAST(({e}) AS BIGINT) DIV {band.eps} - IF(({e}) % {band.eps} < 0, 1, 0)"
    select = f"SELECT /*+ REPARTITION({tasks}, cell__, deal__) */ * FROM (SELECT *, "
    left = f"({select}try_add({cell(band.left.expr)}, step__) AS cell__, pmod(xxhash64(rid__), {DEALT}L) AS deal__ FROM native_{band.left.alias} LATERAL VIEW explode(array(-1L, 0L, 1L)) AS step__))"
    right = f"({select}{cell(band.right.expr)} AS cell__ FROM native_{band.right.alias} LATERAL VIEW explode(sequence(0L, {DEALT - 1}L)) AS deal__))"
    return {band.left.alias: left, band.right.alias: right}


def _text(p: P.Compare) -> str:
    name = lambda s: f"{s.alias}.{s.expr}" if s.expr.isidentifier() else s.expr
    if p.op == "band":
        return f"abs({name(p.left)} - {name(p.right)}) < {p.eps}"
    return f"{name(p.left)} {p.op} {name(p.right)}"
