"""Ranked answers of an acyclic theta-join: bottom-up pass, cut, and beam.

Values are structs (w, x.., r..): the combined weight, lexicographic slots, and the row
ids of the subtree in the order of the atoms, so that ties break the same way
everywhere and a struct comparison is the whole ranking.

1. Bottom-up: under every row its best completion, by folding each edge (``fold``). The
   best root row is the first answer already.
2. Cut: different rows of one atom lie in different answers, so the k best root rows
   bound the k-th answer; going down, each atom keeps the k rows that lie in the best
   answers, again by a fold, from the few rows above to all rows below.
3. Beam: the k best prefixes in tree order, extended by what is left of the next atom.
   A dropped prefix has k better ones, each with an answer of its own.

After the passes nothing is larger than k rows per atom. For a small k the beam joins
these tables on the condition itself. For a large one it goes through the nodes of their
connector: (prefix, node) pairs are cut to k by the node's best target, and the i-th
prefix of a node meets only the k / i best targets of it, so that there are about k log k
candidates and never k * k.

All passes work on row ids that are whole numbers: ids of another type are numbered in
their order once, and named again in the answers. What passes hand on is written to the
shared folder, so that a lost executor costs its tasks only.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans import statistics
from ..plans.jointree import PlanTree, plan_tree
from ..plans.predicates import Compare, Opaque, Side, to_column
from ..plans.query import Query, Rank
from ..sources.staging import Staging
from . import connectors, ranks
from . import fold as folds
from .joins import merged

#: Answers up to which the beam joins its tables directly; affects the cost, not the result.
SMALL_K = 4096


def key_name(side) -> str:
    """The column that holds an expression of an atom."""
    return "k_" + "".join(c if c.isalnum() else f"_{ord(c):x}_" for c in side.expr)


def prepare(query: Query, alias: str, sides: list) -> DataFrame:
    """rid, w (lifted), x (if lexicographic) and the key columns of an atom."""
    atom = query.atom(alias)
    df = atom.df.where(atom.where) if atom.where else atom.df
    columns = [F.expr(atom.rid).alias("rid"), query.rank.lift(F.expr(atom.weight)).alias("w")]
    if query.rank.name == "lex":
        columns.append(F.expr(atom.lex or atom.weight).alias("x"))
    columns += [F.expr(s.expr).alias(key_name(s)) for s in dict.fromkeys(sides)]
    df = df.select(*columns).where("w is not null")
    if dict(df.dtypes)["w"] in ("double", "float"):
        df = df.where(~F.isnan("w"))
    return df


def edge_terms(tree: PlanTree, parent: str, child: str) -> list[list[tuple]]:
    """The edge's terms with key columns, seen from the parent."""
    out = []
    for term in tree.conditions[parent, child]:
        one = []
        for p in term:
            if isinstance(p, Opaque):
                one.append((p, parent, child))
            else:
                p = p.seen_from(parent)
                one.append((p, key_name(p.left), key_name(p.right)))
        out.append(one)
    return out


def flipped(terms: list[list[tuple]]) -> list[list[tuple]]:
    return [[(Compare({"<": ">", "<=": ">=", ">": "<", ">=": "<="}.get(p.op, p.op), p.right, p.left, p.eps), b, a) for p, a, b in term] for term in terms]


class KnownValues(folds.Values):
    """Extents and codes of comparisons, found once on a query's whole relations."""

    def __init__(self, passes: Passes):
        super().__init__(passes.staging)
        self.passes, self._extents, self._codings = passes, {}, {}

    def _name(self, p: Compare) -> tuple:
        return tuple(sorted((str(self.passes.base(s.alias)), s.expr) for s in (p.left, p.right)))

    def _both(self, p: Compare) -> DataFrame:
        one, other = (self.passes.rows(s.alias).select(F.col(key_name(s)).alias("v")) for s in (p.left, p.right))
        return one if len(set(self._name(p))) == 1 else one.unionByName(other)

    def extent(self, pred: tuple, s: DataFrame, t: DataFrame):
        name = self._name(pred[0])
        if name not in self._extents:
            self._extents[name] = ranks.extent(self._both(pred[0]))
        return self._extents[name]

    def coding(self, pred: tuple, s: DataFrame, t: DataFrame, tag: str):
        name = self._name(pred[0])
        if name not in self._codings:
            self._codings[name] = ranks.coding(self._both(pred[0]), self.extent(pred, s, t), self.staging, f"codes-{len(self._codings)}")
        return self._codings[name]


@dataclass
class Passes:
    """State of a query's passes over a plan tree."""

    query: Query
    tree: PlanTree
    staging: Staging
    up: dict[str, DataFrame] = field(default_factory=dict)
    reduced: dict[str, DataFrame] = field(default_factory=dict)
    ranges: int | None = None
    named: dict[str, DataFrame] = field(default_factory=dict)
    _bases: dict[tuple, DataFrame] = field(default_factory=dict)
    _groups: dict[tuple, int] = field(default_factory=dict)

    def __post_init__(self):
        self.known = KnownValues(self) if self.staging is not None else None

    @property
    def lex(self) -> bool:
        return self.query.rank.name == "lex"

    def value(self, own: list[tuple[str, Column, Column | None, Column]], structs: list[tuple[list[int], Column]]) -> Column:
        """A struct from single rows (alias, w, x, rid) and from structs with their slots."""
        rank = self.query.rank
        weights = [w for _, w, _, _ in own] + [c["w"] for _, c in structs]
        slots: dict[int, tuple] = {self.query.index(a): (x, r) for a, _, x, r in own}
        for held, c in structs:
            for k in held:
                slots[k] = (c[f"x{k}"] if self.lex else None, c[f"r{k}"])
        fields = [rank.combine(weights).alias("w")]
        if self.lex:
            fields += [slots[k][0].alias(f"x{k}") for k in sorted(slots)]
        return F.struct(*fields, *[slots[k][1].alias(f"r{k}") for k in sorted(slots)])

    def own(self, alias: str) -> tuple:
        return (alias, F.col("w"), F.col("x") if self.lex else None, F.col("rid"))

    def sides(self, alias: str) -> list:
        found = []
        for terms in self.tree.conditions.values():
            found += [s for term in terms for p in term for s in (p.sides() if isinstance(p, Opaque) else (p.left, p.right)) if s.alias == alias]
        return found

    def keys(self, alias: str) -> list[str]:
        return [key_name(s) for s in dict.fromkeys(self.sides(alias))]

    def base(self, alias: str) -> tuple:
        """What atoms that read the same rows have in common."""
        atom = self.query.atom(alias)
        return (id(atom.df), atom.where, atom.rid, atom.weight, atom.lex)

    def rows(self, alias: str) -> DataFrame:
        """``prepare`` with whole numbers as ids; atoms over the same rows share one numbering."""
        own = prepare(self.query, alias, self.sides(alias))
        if dict(own.dtypes)["rid"] in ("bigint", "int", "smallint", "tinyint"):
            return own
        if self.base(alias) not in self._bases:
            every = [Side(alias, s.expr) for a in self.query.atoms if self.base(a.alias) == self.base(alias) for s in self.sides(a.alias)]
            self._bases[self.base(alias)] = folds.placed(prepare(self.query, alias, every), "rid", "_id", self.staging, f"ids-{alias}")
        numbered = self._bases[self.base(alias)]
        self.named[alias] = numbered.select("_id", "rid")
        return numbered.drop("rid").withColumnRenamed("_id", "rid").select(*own.columns)

    def sizer(self, parent: str, child: str):
        """Key ranges for a term of an edge, from the largest groups of the atoms; each is counted once."""
        if self.ranges is not None:
            return self.ranges

        def group(alias: str, columns: list[str]) -> int:
            name = (*self.base(alias), *columns)
            if name not in self._groups:
                self._groups[name] = folds.largest_group(self.rows(alias), columns)
            return self._groups[name]

        def ranges(term: list[tuple]) -> int:
            sides = {parent: [], child: []}
            for p, _, _ in term:
                if p.op == "=":
                    for s in (p.left, p.right):
                        sides[s.alias].append(key_name(s))
            if len(sides[parent]) == len(term):
                return 1
            return folds.RANGES if sum(group(a, c) for a, c in sides.items()) > folds.SPLIT else 1

        return ranges

    def bottom_up(self, keep_root: bool = True) -> DataFrame:
        """For each atom its rows that have a completion, with ``pi`` and the children's shares m_<child>; done once."""
        order = [a for a in reversed(self.tree.preorder()) if a not in self.up]
        for alias in order:
            rows = self.rows(alias)
            parts = []
            for child in self.tree.children[alias]:
                below = self.up[child].withColumn("val", F.col("pi"))
                rows = folds.fold(rows, below, edge_terms(self.tree, alias, child), "min", f"m_{child}", self.staging, f"up-{alias}-{child}", self.sizer(alias, child), "_n" if "_n" in below.columns else None, self.known)
                parts.append((self.tree.subtree(child), F.col(f"m_{child}")))
            rows = rows.withColumn("pi", self.value([self.own(alias)], parts))
            parent = self.tree.parent(alias)
            if parent is None:
                self.up[alias] = self.staging.save(rows, f"up-{alias}") if keep_root else rows
            elif folds.expands(edge_terms(self.tree, parent, alias)):
                self.up[alias] = folds.placed(rows, "pi", "_n", self.staging, f"up-{alias}")
            else:
                self.up[alias] = self.staging.save(rows, f"up-{alias}")
        return self.up[self.tree.root]

    def cut(self, k: int) -> None:
        """Each atom's rows that can occur in the k best answers, at most k of them."""
        root = self.tree.root
        self.reduced[root] = self.staging.save(self.bottom_up().orderBy("pi").limit(k), f"cut-{k}-{root}")
        n, worst = self.reduced[root].agg(F.count(F.lit(1)), F.max("pi.w")).first()
        bound = worst if n >= k and self.query.rank.name == "sum" else None
        outside: dict[str, Column | None] = {root: None}
        for alias in self.tree.preorder():
            above = self.reduced[alias]
            for child in self.tree.children[alias]:
                rest = [(self.tree.subtree(c), F.col(f"m_{c}")) for c in self.tree.children[alias] if c != child]
                if outside[alias] is not None:
                    rest.append((sorted(set(range(len(self.query.atoms))) - set(self.tree.subtree(alias))), F.col("up")))
                given = above.withColumn("val", self.value([self.own(alias)], rest))
                below = self.up[child]
                if bound is not None:
                    least = given.agg(F.min("val.w")).first()[0]
                    if least is not None:  # even with the lightest surroundings these are too heavy
                        below = below.where(F.col("pi.w") <= F.lit(bound - least))
                terms = flipped(edge_terms(self.tree, alias, child))
                kept = folds.fold(below, given, terms, "min", "up", self.staging, f"down-{k}-{alias}-{child}", self.sizer(child, alias), None, self.known)
                inside = self.tree.subtree(child)
                through = self.value([], [(inside, F.col("pi")), (sorted(set(range(len(self.query.atoms))) - set(inside)), F.col("up"))])
                self.reduced[child] = self.staging.save(kept.withColumn("thru", through).orderBy("thru").limit(k).drop("thru"), f"cut-{k}-{child}")
                outside[child] = F.col("up")

    def _table(self, alias: str) -> DataFrame:
        """The reduced rows of an atom under names of its own."""
        i = self.query.index(alias)
        columns = [F.col("rid").alias(f"rid{i}"), F.col("w").alias(f"w{i}"), *[F.col(c).alias(f"{c}_{i}") for c in self.keys(alias)], *[F.col(f"m_{c}") for c in self.tree.children[alias]]]
        return self.reduced[alias].select(*columns, F.col("pi").alias(f"pi{i}"), *([F.col("x").alias(f"xx{i}")] if self.lex else []))

    def _single(self, alias: str) -> tuple:
        i = self.query.index(alias)
        return (alias, F.col(f"w{i}"), F.col(f"xx{i}") if self.lex else None, F.col(f"rid{i}"))

    def beam(self, k: int) -> DataFrame:
        """(weight struct ``total``) of the k best answers."""
        order = self.tree.preorder()
        prefix, done = self._table(order[0]), [order[0]]
        for alias in order[1:]:
            step = self._condition_step if k <= SMALL_K else self._node_step
            prefix = step(prefix, done, alias, k)
            done.append(alias)
            pending = [c for a in done for c in self.tree.children[a] if c not in done]
            total = self.value([self._single(a) for a in done], [(self.tree.subtree(c), F.col(f"m_{c}")) for c in pending])
            prefix = prefix.withColumn("total", total).orderBy("total").limit(k)
            if alias != order[-1]:
                prefix = prefix.drop("total")
                prefix = self.staging.save(prefix, f"beam-{k}-{alias}") if k > SMALL_K else prefix
        if len(order) == 1:
            prefix = prefix.withColumn("total", self.value([self._single(order[0])], []))
        return prefix.select("total")

    def _condition_step(self, prefix: DataFrame, done: list[str], alias: str, k: int) -> DataFrame:
        """Prefixes joined with the next atom on the condition; both sides have k rows at most."""
        parent = self.tree.parent(alias)
        i, j = self.query.index(parent), self.query.index(alias)
        terms = edge_terms(self.tree, parent, alias)
        cond, shared = None, None
        for term in terms:
            one = F.lit(True)
            for p, a, b in term:
                one = one & to_column(p, F.col(f"{a}_{i}"), F.col(f"{b}_{j}"))
            cond = one if cond is None else cond | one
        for p, a, b in terms[0]:
            if p.op == "=" and all((p, a, b) in t for t in terms):
                c = F.col(f"{a}_{i}") == F.col(f"{b}_{j}")
                shared = c if shared is None else shared & c
        return prefix.join(self._table(alias), cond if shared is None else shared & cond)

    def _node_step(self, prefix: DataFrame, done: list[str], alias: str, k: int) -> DataFrame:
        """As above, by way of the nodes of the edge's connector."""
        parent = self.tree.parent(alias)
        i, j = self.query.index(parent), self.query.index(alias)
        left, right = (self.reduced[a].select("rid", *self.keys(a)) for a in (parent, alias))
        graph = connectors.build(left, right, edge_terms(self.tree, parent, alias), "binary", f"beam-{parent}-{alias}")
        e_in, e_out = graph.parts
        targets = e_out.join(merged(self._table(alias)), F.col("rid_t") == F.col(f"rid{j}")).drop("rid_t")
        targets = targets.withColumn("_j", F.row_number().over(Window.partitionBy("node").orderBy(f"pi{j}"))).where(F.col("_j") <= k)
        targets = self.staging.save(targets, f"beam-{k}-{alias}-targets")
        best = targets.where("_j = 1").select("node", F.col(f"pi{j}").alias("_best"))
        others = [(self.tree.subtree(c), F.col(f"m_{c}")) for a in done for c in self.tree.children[a] if c not in done and c != alias]
        singles = [self._single(a) for a in done]
        hops = prefix.join(merged(e_in), F.col("rid_s") == F.col(f"rid{i}")).drop("rid_s").join(merged(best), "node")
        hops = hops.withColumn("_rest", self.value(singles, others)).withColumn("_top", self.value(singles, [*others, (self.tree.subtree(alias), F.col("_best"))]))
        # a pair of terms can bring one answer each, so as many more are kept
        hops = hops.orderBy("_top").limit(k * graph.dup_factor).drop("_top", "_best")
        hops = hops.withColumn("_i", F.row_number().over(Window.partitionBy("node").orderBy("_rest"))).drop("_rest")
        hops = hops.withColumn("_a", F.floor(F.log2(F.col("_i") + F.lit(0.5))).cast("int"))
        # the i-th prefix needs k / i targets: rows of 2**a <= i < 2**(a + 1) meet the first k / 2**a
        reach = F.floor(F.log2(F.lit(k) / F.col("_j") + F.lit(1e-9))).cast("int")
        dealt = targets.withColumn("_a", F.explode(F.sequence(F.lit(0), F.greatest(reach, F.lit(0)))))
        found = hops.join(merged(dealt), ["node", "_a"]).where(F.col("_i") * F.col("_j") <= k).drop("node", "_a", "_i", "_j")
        return found.dropDuplicates([f"rid{self.query.index(a)}" for a in (*done, alias)]) if graph.dup_factor > 1 else found

    def answers(self, total: DataFrame, k: int) -> DataFrame:
        """rank, weight, rid_1.. of the structs of at most k answers."""
        query = self.query
        flat = total.where("total is not null").select("total.*")
        place = F.row_number().over(Window.orderBy(*flat.columns))
        shown = query.rank.shown(F.col("w")).alias("weight")
        n = range(len(query.atoms))
        lex = [F.col(f"x{i}").alias(f"lex_{i + 1}") for i in n] if self.lex else []
        out = flat.select(place.cast("long").alias("rank"), shown, *lex, *[F.col(f"r{i}").alias(f"rid_{i + 1}") for i in n])
        return self.name_rows(out, {f"rid_{i + 1}": query.atoms[i].alias for i in n}, k)

    def name_rows(self, found: DataFrame, columns: dict[str, str], k: int | None = None) -> DataFrame:
        """The rows' own ids in place of numbers; ``columns``: the alias that a column has ids of."""
        out = found
        for column, alias in columns.items():
            if alias in self.named:
                small = F.broadcast(out) if k is not None and k <= SMALL_K else out  # k rows
                out = self.named[alias].select(F.col("_id").alias(column), F.col("rid").alias("_name")).join(small, column).drop(column).withColumnRenamed("_name", column)
        return out.select(*found.columns)


def top_k(query: Query, k: int, root: str | None = None, ranges: int | None = None) -> DataFrame:
    """rank, weight, rid_1, .., rid_l of the k best answers of an acyclic query.

    ``root``: the atom at the root of the plan tree, the first one unless said; ``"auto"``
    has it chosen by statistics.
    """
    passes = _passes(query, root, ranges)
    if k <= 0:
        return passes.answers(passes.bottom_up(False).select(F.col("pi").alias("total")).limit(0), 0)
    if k == 1:
        return passes.answers(passes.bottom_up(False).agg(F.min("pi").alias("total")), 1)
    passes.cut(k)
    return passes.answers(passes.beam(k), k)


def top_k_bottleneck(query: Query, k: int, root: str | None = None) -> DataFrame:
    """As ``top_k`` for a bottleneck ranking, with ties in the order of the ids.

    A better part need not make a better whole here, so ids can't break ties on the way.
    The k-th weight comes first; then all answers that are better, fewer than k, and of
    the answers at that weight the first k by their ids, split by the first atom that has it.
    """
    if query.rank.name != "bottleneck":
        raise ValueError("a bottleneck ranking is asked for")
    found = top_k(query, k, root).agg(F.max("rank").alias("n"), F.max_by("weight", "rank").alias("worst")).first()
    if not found["n"]:
        return top_k(query, 0, root)
    worst, better = found["worst"], (">" if query.rank.desc else "<")

    def part(ops: list[str], rank: Rank, keep: int) -> DataFrame:
        put = lambda a, op: replace(a, where=" AND ".join(f"({x})" for x in ([a.where] if a.where else []) + [f"{a.weight} {op} {worst}"]), lex=a.rid)
        return top_k(replace(query, atoms=[put(a, op) for a, op in zip(query.atoms, ops, strict=True)], rank=rank), keep, root)

    n = len(query.atoms)
    ids = [f"rid_{i + 1}" for i in range(n)]
    out = part([better] * n, query.rank, k).select("weight", *ids)
    for i in range(n):
        tied = part([better] * i + ["="] + [better + "="] * (n - i - 1), Rank.lex(), k)
        out = out.unionByName(tied.select(F.lit(worst).alias("weight"), *ids))
    by = [F.col("weight").desc() if query.rank.desc else F.col("weight"), *ids]
    return out.orderBy(*by).limit(k).select(F.row_number().over(Window.orderBy(*by)).cast("long").alias("rank"), "weight", *ids)


def _passes(query: Query, root: str | None, ranges: int | None = None) -> Passes:
    if root == "auto":
        root = statistics.choose_root(query)
    tree = plan_tree(query, root)
    return Passes(tree.query, tree, Staging(query.atoms[0].df.sparkSession, "ranked"), ranges=ranges)


def dp_values(query: Query, alias: str, root: str | None = None) -> DataFrame:
    """rid and weight of the best completion under each row of an atom."""
    passes = _passes(query, root)
    passes.bottom_up()
    return passes.name_rows(passes.up[alias].select("rid", query.rank.shown(F.col("pi.w")).alias("best")), {"rid": alias})


def count_answers(query: Query, root: str | None = None, ranges: int | None = None, exact: bool = False) -> DataFrame:
    """(answers): the size of the join, by sums in place of minima; nothing is materialised.

    A 64-bit number, or a decimal of 38 digits with ``exact`` or where 64 bits can't hold it.
    Sums are 64-bit where the product of the atoms' sizes shows that they can't overflow.
    """
    passes = _passes(query, root, ranges)
    tree, done, most = passes.tree, {}, 1
    sizes: dict[tuple, int] = {}
    for a in passes.query.atoms:
        if passes.base(a.alias) not in sizes:
            sizes[passes.base(a.alias)] = passes.rows(a.alias).count()
        most *= max(1, sizes[passes.base(a.alias)])
    # terms are added and subtracted, up to two to the power of their number
    terms = max((len(t) for t in tree.conditions.values()), default=1)
    kind = "long" if most << terms < 1 << 62 else "decimal(38,0)"
    for alias in reversed(tree.preorder()):
        rows = passes.rows(alias).withColumn("n", F.lit(1).cast(kind))
        for child in tree.children[alias]:
            below = done[child].withColumn("val", F.col("n"))
            rows = folds.fold(rows, below, edge_terms(tree, alias, child), "sum", "m", passes.staging, f"count-{alias}-{child}", passes.sizer(alias, child), None, passes.known)
            rows = rows.withColumn("n", (F.col("n") * F.col("m")).cast(kind)).drop("m")
        done[alias] = passes.staging.save(rows, f"count-{alias}") if tree.children[alias] and alias != tree.root else rows
    total = done[tree.root].agg(F.coalesce(F.sum("n"), F.lit(0)).cast("decimal(38,0)" if exact or kind != "long" else "long").alias("answers"))
    if exact or kind == "long":
        return total
    total = passes.staging.save(total, "count")
    return total if total.first()["answers"] >= 1 << 63 else total.select(F.col("answers").cast("long"))


def materialize(found: DataFrame, query: Query, columns: dict[str, list[str]]) -> DataFrame:
    """Adds payload columns to answers: alias -> columns; one lookup join per atom named."""
    for alias, wanted in columns.items():
        atom, i = query.atom(alias), query.index(alias) + 1
        rows = atom.df.select(F.expr(atom.rid).alias(f"rid_{i}"), *[F.col(c).alias(f"{alias}_{c}") for c in wanted])
        found = rows.join(F.broadcast(found), f"rid_{i}")  # k rows
    return found
