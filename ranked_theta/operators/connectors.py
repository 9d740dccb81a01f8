"""Connector graphs: compact DAGs whose paths from S to T are the joining pairs.

All are closed forms over codes of the join values; nothing recurses. A node is the term
it belongs to, the equality key, and a path of (level, prefix) choices, one per
non-equality comparison, so that equality of node ids is never more than the structure
says. ``build`` gives edges (rid_s, node) and (node, rid_t), for the multiway connector
with an edge relation between two kinds of nodes in the middle.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.predicates import Compare, Opaque, to_column
from ..sources.staging import Staging
from . import ranks
from .joins import merged

METHODS = ("auto", "binary", "median", "multiway", "two-way", "chain", "direct")
#: Pairs an edge from which on the ends of a node are bundled before they are joined, the ends in a bundle, the ends of
#: a node that one task gathers, and pairs of a task. Costs only, same pairs.
DENSE, BUNDLE, GATHERED, PAIRS = 64, 512, 1 << 16, 1 << 26


def one_by_one(pairs: DataFrame, carried: tuple[str, ...] = ()) -> DataFrame:
    """Pairs in the form of ``Connector.fans``, a target in a row."""
    return pairs.select("rid_s", F.struct(*[F.array(c).alias(c) for c in ("rid_t", *carried)]).alias("fan"))


@dataclass
class Ends:
    """Where the split of a conjunction's last comparison starts: (node, code, rid_s) and (node, code, rid_t) by the nodes of the comparisons before."""

    s: DataFrame
    t: DataFrame
    op: str


@dataclass
class Connector:
    """``parts``: edge relations from the source side to the target side; ``ends``, ``terms``: what pairs are listed from where there is more than one comparison or term."""

    parts: list[DataFrame]
    depth: int
    dup_factor: int
    layered: bool = True
    notes: dict = field(default_factory=dict)
    ends: Ends | None = None
    terms: list[Connector] = field(default_factory=list)

    def size(self) -> DataFrame:
        """(nodes, edges): the implementation-neutral size, middle nodes only counted once."""
        edges = None
        for p in self.parts:
            one = p.agg(F.count(F.lit(1)).alias("n"))
            edges = one if edges is None else edges.unionByName(one)
        nodes = None
        for p in self.parts:
            for c in p.columns:
                if not c.startswith("rid"):
                    one = p.select(F.col(c).alias("node"))
                    nodes = one if nodes is None else nodes.unionByName(one)
        n_nodes = nodes.agg(F.countDistinct("node").alias("nodes")) if nodes is not None else edges.sparkSession.createDataFrame([(0,)], "nodes long")
        return n_nodes.crossJoin(F.broadcast(edges.agg(F.sum("n").cast("long").alias("edges"))))

    def pairs(self, carried: tuple[str, ...] = ()) -> DataFrame:
        """(rid_s, rid_t) of all paths, by equi-joins alone; ``carried``: columns that the last edges have besides."""
        if not self.layered:
            raise ValueError("edges skip layers: this connector has no form as a chain of equi-joins")
        if self.terms:
            return reduce(DataFrame.unionByName, [c.pairs(carried) for c in self.terms])
        if self.ends is not None:
            return _split(self.ends).select("rid_s", "rid_t", *carried)
        out = self.parts[0]
        for k, p in enumerate(self.parts[1:]):
            left = self.parts[k].columns[-1]
            out, p = out.withColumnRenamed(left, f"_j{k}"), p.withColumnRenamed(p.columns[0], f"_j{k}")
            dealt = _dealt(out, p, f"_j{k}") if k == len(self.parts) - 2 else None
            out = dealt if dealt is not None else out.join(merged(p), f"_j{k}").drop(f"_j{k}")
        return out.select("rid_s", "rid_t", *carried)

    def fans(self, carried: tuple[str, ...] = ()) -> DataFrame:
        """(rid_s, fan): the same pairs, many targets of a source in a row, as arrays rid_t and carried; a source has several rows."""
        if self.layered and self.terms:
            return reduce(DataFrame.unionByName, [c.fans(carried) for c in self.terms])
        if self.layered and self.ends is not None:
            whole = _fitting(self.ends).where(F.size("_fit") > 0)
            parts = [F.col("_fit")[c].alias(c) for c in ("rid_t", *carried)] if carried else [F.col("_fit").alias("rid_t")]
            return whole.select("rid_s", F.struct(*parts).alias("fan"))
        return one_by_one(self.pairs(carried), carried)

    def carry(self, rows: DataFrame) -> None:
        """The other columns of ``rows`` go along with their ``rid_t``."""
        more = lambda df: df.join(merged(rows), "rid_t").select(*df.columns, *[c for c in rows.columns if c != "rid_t"])
        self.parts[-1] = more(self.parts[-1])
        if self.ends is not None:
            self.ends.t = more(self.ends.t)
        for c in self.terms:
            c.carry(rows)

    def layers(self) -> list[DataFrame]:
        """The vertices of each layer: sources, nodes, targets; an edge never skips one."""
        if not self.layered:
            raise ValueError("a vertex of this connector has no layer of its own")
        return [self.parts[0].select(self.parts[0].columns[0]).distinct(), *[p.select(p.columns[-1]).distinct() for p in self.parts]]

    def paths_per_pair(self) -> DataFrame:
        """(paths, pairs): how many pairs have how many paths."""
        return self.pairs().groupBy("rid_s", "rid_t").agg(F.count(F.lit(1)).alias("paths")).groupBy("paths").agg(F.count(F.lit(1)).alias("pairs"))


def _cut(ends: str, size: int) -> Column:
    """An array in pieces."""
    return F.transform(F.sequence(F.lit(0), F.floor((F.size(ends) - 1) / size).cast("int")), lambda i: F.slice(ends, i * size + 1, size))


def _bundles(edges: DataFrame, node: str, most: int, out: str, first: tuple[str, ...] = ()) -> DataFrame:
    """(node, out, its place): the other ends of a node's edges, ``BUNDLE`` of them in a row; ``most``: edges of the largest node.

    Ends are sorted, by the columns ``first`` before others, and then cut, so that a task that runs again makes the same bundles.
    """
    ends = [*first, *[c for c in edges.columns if c != node and c not in first]]
    way = F.pmod(F.xxhash64(*ends), F.lit(-(-most // GATHERED)).cast("long"))
    rows = edges.groupBy(node, way.alias("_way")).agg(F.sort_array(F.collect_list(F.struct(*ends))).alias("_all"))
    rows = rows.select(node, "_way", F.posexplode(_cut("_all", BUNDLE)).alias("_at", out))
    bare = F.col(out)[ends[0]] if len(ends) == 1 else F.col(out)  # a struct an end costs memory and time, but keeps nulls in the list
    return rows.select(node, bare.alias(out), F.struct("_way", "_at").alias(f"{out}_at"))


def _dealt(left: DataFrame, right: DataFrame, node: str) -> DataFrame | None:
    """The join of two edge relations over ``node`` if it has many pairs an edge, else None.

    A node near the root holds half of all pairs, and a join by node would leave them to one
    task. Bundles of ends are joined instead and dealt out before they become pairs. Pairs of
    a bundle come in turns of the same targets, which files hold in few bytes.
    """
    n = lambda df, out: df.groupBy(node).agg(F.count(F.lit(1)).alias(out))
    pairs = F.col("_n").cast("double") * F.col("_m")
    known = n(left, "_n").join(merged(n(right, "_m")), node).agg(F.sum(pairs), F.sum("_n"), F.sum("_m"), F.max("_n"), F.max("_m")).first()
    if known[0] is None or known[0] < DENSE * (known[1] + known[2]):
        return None
    tasks = max(int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-int(known[0]) // PAIRS))
    both = _bundles(left, node, known[3], "_s").join(merged(_bundles(right, node, known[4], "_t")), node)
    both = both.repartition(tasks, node, "_s_at", "_t_at").sortWithinPartitions(node, "_t_at", "_s_at")
    # compiled code holds all pairs of a row before it hands on the first: a row of few sources keeps them in the cache
    both = both.select(F.explode(_cut("_s", max(1, BUNDLE // 32))).alias("_s"), "_t")
    for side, edges in (("_s", left), ("_t", right)):
        ends, others = [c for c in edges.columns if c != node], [c for c in both.columns if c != side]
        both = both.select(*others, F.explode(side).alias(ends[0])) if len(ends) == 1 else both.select(*others, F.explode(side).alias(side)).select(*others, f"{side}.*")
    return both


def _split(ends: Ends) -> DataFrame:
    """The pairs of ``_fitting``."""
    both = _fitting(ends)
    sources, targets = [c for c in both.columns if c != "_fit"], [c for c in ends.t.columns if c not in ("node", "code")]
    if len(targets) == 1:
        return both.select(*sources, F.explode("_fit").alias(targets[0]))
    return both.select(*sources, F.explode("_fit").alias("_t")).select(*sources, "_t.*")


def _fitting(ends: Ends) -> DataFrame:
    """A source and an array ``_fit`` of targets in a row, by a split that goes on within each node, over its ends in the order of their codes.

    The nodes that a source of an inequality turns away from lie side by side, so that all
    their targets are one slice of the node's targets, and the turns find where it begins.
    So the nodes of the last comparison, some for each bit and end, are never written out:
    bundles of sorted ends are joined by the node before it, and dealt over tasks.
    """
    n = lambda df, out: df.groupBy("node").agg(F.count(F.lit(1)).alias(out))
    known = n(ends.s, "_n").join(merged(n(ends.t, "_m")), "node").agg(F.sum(F.col("_n").cast("double") * F.col("_m")), F.max("_n"), F.max("_m")).first()
    pairs, most_s, most_t = known[0] or 0, known[1] or 1, known[2] or 1
    tasks = max(int(ends.s.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-int(pairs) // PAIRS))
    s, t = _bundles(ends.s, "node", most_s, "_s", ("code",)), _bundles(ends.t, "node", most_t, "_t", ("code",))
    others = {"s": [c for c in ends.s.columns if c not in ("node", "code")], "t": [c for c in ends.t.columns if c not in ("node", "code")]}
    bare = lambda e: e[others["t"][0]] if len(others["t"]) == 1 else F.struct(*[e[c].alias(c) for c in others["t"]])
    t = t.select("node", F.transform("_t", lambda e: e["code"]).alias("_c"), F.transform("_t", bare).alias("_t"), "_t_at")
    least = lambda c: F.get(c, F.lit(0))
    most = lambda c: F.get(c, F.size(c) - 1)
    s_low, s_high, t_low, t_high = least(F.col("_s"))["code"], most(F.col("_s"))["code"], least(F.col("_c")), most(F.col("_c"))
    meet = {"<": s_low < t_high, "<=": s_low <= t_high, ">": s_high > t_low, ">=": s_high >= t_low, "!=": (s_low != t_high) | (s_high != t_low)}[ends.op]
    both = s.join(merged(t), "node").where(meet).repartition(tasks, "node", "_s_at", "_t_at").sortWithinPartitions("node", "_t_at", "_s_at")
    both = both.select(F.explode(_cut("_s", max(1, BUNDLE // 32))).alias("_s"), "_c", "_t").select(F.explode("_s").alias("_s"), "_c", "_t")

    def turns(strict: bool) -> Column:
        """How many codes are less than the source's (or equal to it, if not ``strict``)."""
        code, steps = F.col("_s")["code"], F.array(*[F.lit(1 << k) for k in reversed(range(BUNDLE.bit_length()))])

        def turn(at: Column, step: Column) -> Column:
            c = F.get("_c", at + step - 1)  # null behind the last
            return F.when((c < code) if strict else (c <= code), at + step).otherwise(at)

        return F.aggregate(steps, F.lit(0), turn)

    below, upto = F.col("_below"), F.col("_upto")
    needed = {"<": ("_upto",), "<=": ("_below",), ">": ("_below",), ">=": ("_upto",), "!=": ("_below", "_upto")}[ends.op]
    both = both.withColumns({c: turns(c == "_below") for c in needed})
    front, back = lambda n: F.slice("_t", F.lit(1), n), lambda n: F.slice("_t", n + 1, F.size("_t") - n)
    fit = {"<": lambda: back(upto), "<=": lambda: back(below), ">": lambda: front(below), ">=": lambda: front(upto), "!=": lambda: F.concat(front(below), back(upto))}[ends.op]()
    sources = [F.col("_s")[c].alias(c) for c in others["s"]]
    return both.select(*sources, fit.alias("_fit"))


def _node(g: Column, path: list[Column]) -> Column:
    return F.struct(g.alias("g"), F.array(*path).alias("path"))


def _choice(h: Column, prefix: Column) -> Column:
    return F.struct(h.cast("int").alias("h"), prefix.cast("long").alias("p"))


def shift(code: Column, by: Column) -> Column:
    return F.call_function("shiftright", code, by.cast("int"))


def levels(df: DataFrame, code: str, op: str, bits: int, source: bool, out: str) -> DataFrame:
    """One row per node choice of a comparison: the highest bit in which two codes differ decides it.

    A source of ``<`` offers each level whose bit is 0, a target each whose bit is 1; for
    ``>`` the sides swap; the non-strict forms also meet in a node of their own value; for
    ``!=`` a node keeps the source's bit and any difference will do.
    """
    if op == "=":
        return df.withColumn(out, _choice(F.lit(-2), F.col(code)))
    c, h = F.col(code), F.col("_h")
    rows = df.withColumn("_h", F.explode(F.sequence(F.lit(-1 if op in ("<=", ">=") else 0), F.lit(bits - 1))))
    bit = shift(c, F.greatest(h, F.lit(0))).bitwiseAND(F.lit(1))
    if op == "!=":
        kept = bit if source else F.lit(1) - bit
        rows = rows.withColumn(out, _choice(h, shift(c, h + 1) * 2 + kept))
    else:
        wanted = 0 if (op in ("<", "<=")) == source else 1
        rows = rows.where((h == -1) | (bit == wanted)).withColumn(out, _choice(h, F.when(h == -1, c).otherwise(shift(c, h + 1))))
    return rows.drop("_h")


def cells(df: DataFrame, key: str, eps: int, source: bool, out: str) -> DataFrame:
    """Bands by cells of width eps: the own cell always joins, the two next ones leave one inequality each.

    Gives the part (cell and kind) and the value that is left to compare as ``<``.
    """
    k, cell = F.col(key), (F.col(key) - F.pmod(F.col(key), F.lit(eps).cast("long"))).cast("long")
    if source:  # kind 0: same cell; 1: target in the next cell, t < s + eps; 2: in the one before, t > s - eps
        made = F.array(F.struct(F.lit(0).alias("kind"), cell.alias("cell"), F.lit(0).cast("long").alias("v")), F.struct(F.lit(1).alias("kind"), (cell + F.lit(eps).cast("long")).alias("cell"), (k + F.lit(eps)).cast("long").alias("v")), F.struct(F.lit(2).alias("kind"), (cell - F.lit(eps).cast("long")).alias("cell"), (k - F.lit(eps)).cast("long").alias("v")))
    else:
        made = F.array(*[F.struct(F.lit(n).alias("kind"), cell.alias("cell"), (F.lit(0) if n == 0 else k).cast("long").alias("v")) for n in range(3)])
    return df.withColumn(out, F.explode(made))


def _segments(bits: int) -> list[tuple[int, int]]:
    """(low, width) of digits: the top half of the bits, then half of the rest, and so on."""
    out, left = [], bits
    while left > 0:
        take = -(-left // 2)
        out.append((left - take, take))
        left -= take
    return out


def _keys(df: DataFrame, rid: str, columns: list[tuple[str, str]]) -> DataFrame:
    """rid and the columns under new names, rows with nulls left out."""
    rows = df.select(F.col(rid).alias("rid"), *[F.col(c).alias(name) for c, name in columns])
    for _, name in columns:
        rows = rows.where(F.col(name).isNotNull())
    return rows


def _ends(s: DataFrame, t: DataFrame, pred: tuple[Compare, str, str], path: list[str]) -> Ends:
    """The ends of coded rows in the nodes of ``path``."""
    p, a, b = pred
    node = _node(F.col("_g"), [F.col(c) for c in path]).alias("node")
    return Ends(s.select(node, F.col(a).alias("code"), F.col("rid").alias("rid_s")), t.select(node, F.col(b).alias("code"), F.col("rid").alias("rid_t")), p.op)


def _held(choice: Column, bit: int) -> tuple[Column, Column]:
    """First and last code below a node choice, on the side of ``bit``."""
    h, p = choice["h"], choice["p"]
    size = F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(h, F.lit(0)))
    first = F.when(h == -1, p).otherwise((p * 2 + bit) * size)
    return first, first + F.when(h == -1, F.lit(0)).otherwise(size - 1)


def _between(rest: list[tuple]) -> dict[int, int]:
    """Comparisons that bound one target column from below and from above: place of the second, and of the first."""
    out: dict[int, int] = {}
    for k, (p, _, b) in enumerate(rest):
        for j, (q, _, c) in enumerate(rest[:k]):
            if b == c and {p.op[:1], q.op[:1]} == {"<", ">"} and j not in out and j not in out.values() and k not in out:
                out[k] = j
    return out


def _term(s: DataFrame, t: DataFrame, preds: list[tuple[Compare, str, str]], staging: Staging, tag: str, method: str) -> Connector:
    """The connector of one conjunction; ``preds`` come with the key columns of both sides."""
    # a column may stand in several comparisons, and each is coded on its own
    hard = [(p, a, b) for p, a, b in preds if p.op != "="]
    s, t = _keys(s, "rid", [(a, f"_s{k}") for k, (_, a, _) in enumerate(preds)]), _keys(t, "rid", [(b, f"_t{k}") for k, (_, _, b) in enumerate(preds)])
    preds = [(p, f"_s{k}", f"_t{k}") for k, (p, _, _) in enumerate(preds)]
    equal = [(a, b) for p, a, b in preds if p.op == "="]
    rest = [(p, a, b) for p, a, b in preds if p.op != "="]
    g_s, g_t = F.array(*[F.col(a).cast("string") for a, _ in equal]), F.array(*[F.col(b).cast("string") for _, b in equal])
    s, t = s.withColumn("_g", g_s), t.withColumn("_g", g_t)
    last = len(rest) - 1
    bits: dict[int, int] = {}
    gaps: dict[int, tuple[int, int]] = {}
    # codes are found before rows are repeated for nodes; two bounds of a column get codes of one kind, so that their nodes can be held against each other
    within = _between(hard) if method == "binary" else {}
    for k, j in within.items():
        s, t, bits[k] = _bounded(s, t, [rest[j], rest[k]], staging, f"{tag}-{k}")
        bits[j] = bits[k]
        low, high = (rest[j][1], rest[k][1]) if rest[j][0].op[:1] == "<" else (rest[k][1], rest[j][1])
        found = s.agg(F.min(F.col(high) - F.col(low)), F.max(F.col(high) - F.col(low))).first()
        if found[0] is not None:
            gaps[k] = found[0], found[1]
    for k, (p, a, b) in enumerate(rest):
        if k not in bits and p.op != "band" and not (method == "multiway" and k == last):
            s, t, bits[k] = ranks.codes(s, t, a, b, staging, f"{tag}-{k}")
            if method == "median":
                s, t, bits[k] = _median(s, t, a, b, staging, f"{tag}-{k}-median")
    if len(rest) > 1:  # a small file is read by one task, which would make all nodes of its rows
        n = max(1, int(s.sparkSession.conf.get("spark.sql.shuffle.partitions")))
        s, t = s.repartition(n, *s.columns), t.repartition(n, *t.columns)
    path: list[str] = []
    ends = None
    for k, (p, a, b) in enumerate(rest):
        name = f"_p{k}"
        if method == "multiway" and k == last:
            return _multiway(s, t, (p, a, b), path, staging, f"{tag}-{k}")
        if p.op == "band":
            s, t = cells(s, a, p.eps, True, "_c"), cells(t, b, p.eps, False, "_c")
            s, t = s.withColumn("_v", F.col("_c.v")), t.withColumn("_v", F.col("_c.v"))
            s, t, width = ranks.codes(s, t, "_v", "_v", staging, f"{tag}-{k}")
            kind = F.col("_c.kind")
            # kind 1 asks t < s + eps, kind 2 t > s - eps, kind 0 nothing: its codes are equal on both sides
            parts_s, parts_t = [], []
            for n, op in ((0, "="), (1, ">"), (2, "<")):
                parts_s.append(levels(s.where(kind == n), "_v", op, width, True, name))
                parts_t.append(levels(t.where(kind == n), "_v", op, width, False, name))
            s, t = (x[0].unionByName(x[1]).unionByName(x[2]) for x in (parts_s, parts_t))
            cell = lambda df: df.withColumn(f"{name}c", _choice(kind, F.col("_c.cell"))).drop("_c", "_v")
            s, t = cell(s), cell(t)
            path += [f"{name}c", name]
        else:
            if k == last and path:
                ends = _ends(s, t, (p, a, b), path)
            s, t = levels(s, a, p.op, bits[k], True, name), levels(t, b, p.op, bits[k], False, name)
            path.append(name)
            if k in gaps:
                s, t = _nested(s, t, within[k], k, p.op, gaps[k])
    node = _node(F.col("_g"), [F.col(c) for c in path] or [_choice(F.lit(-3), F.lit(0))])
    e_in, e_out = s.select(F.col("rid").alias("rid_s"), node.alias("node")), t.select(node.alias("node"), F.col("rid").alias("rid_t"))
    return Connector([e_in, e_out], 2, 1, ends=ends)


def _bounded(s: DataFrame, t: DataFrame, bounds: list[tuple], staging: Staging, tag: str) -> tuple[DataFrame, DataFrame, int]:
    """As ``ranks.codes``, for the columns of several comparisons together."""
    both = reduce(DataFrame.unionByName, [x.select(F.col(c).alias("v")) for _, a, b in bounds for x, c in ((s, a), (t, b))])
    made = ranks.coding(both, ranks.extent(both), staging, tag, False)
    for _, a, b in bounds:
        s, t = made.apply(s, a), made.apply(t, b)
    return s, t, made.bits


def _nested(s: DataFrame, t: DataFrame, j: int, k: int, op: str, gap: tuple[int, int]) -> tuple[DataFrame, DataFrame]:
    """Without nodes of two bounds that no pair can lead through: for a source their targets don't meet, for a target no source has bounds as far apart.

    ``gap``: least and greatest distance of a source's bounds.
    """
    low, high = (F.col(f"_p{n}") for n in ((k, j) if op[:1] == "<" else (j, k)))
    (low_1, low_n), (high_1, high_n) = _held(low, 1), _held(high, 0)
    s = s.where((low_1 <= high_n) & (high_1 <= low_n))
    (low_1, low_n), (high_1, high_n) = _held(low, 0), _held(high, 1)
    return s, t.where((low_1 + gap[0] <= high_n) & (high_1 <= low_n + gap[1]))


def _median(s: DataFrame, t: DataFrame, a: str, b: str, staging: Staging, tag: str):
    """Codes of the median-pivot tree in place of the bit grid; values are ranked densely first."""
    both = s.select(F.col(a).alias("v")).unionByName(t.select(F.col(b).alias("v")))
    domain, n = ranks.dense_rank_domain(both, "v", staging, tag)
    place = domain.select(F.col("val").alias("v"), ranks.balanced(F.col("rk"), max(n, 1)).alias("code"))
    swap = lambda df, c: df.join(merged(place), F.col(c) == F.col("v")).drop(c, "v").withColumnRenamed("code", c)
    return swap(s, a), swap(t, b), max(1, (max(n, 1) - 1).bit_length())


def _multiway(s: DataFrame, t: DataFrame, pred: tuple[Compare, str, str], path: list[str], staging: Staging, tag: str) -> Connector:
    """Digits instead of bits for the last comparison: a level has one node per digit on each side and edges between digits.

    ``path``: columns with the node choices of the comparisons before. A band leaves a
    comparison in each neighbouring cell, and nothing in its own.
    """
    p, a, b = pred
    pieces = []
    ends = None
    if p.op == "band":
        s, t = cells(s, a, p.eps, True, "_c"), cells(t, b, p.eps, False, "_c")
        s, t = (x.withColumns({"_v": F.col("_c.v"), "_cell": _choice(F.col("_c.kind"), F.col("_c.cell"))}) for x in (s, t))
        s, t, bits = ranks.codes(s, t, "_v", "_v", staging, tag)
        path = [*path, "_cell"]
        pieces = [(*(x.where(F.col("_c.kind") == n) for x in (s, t)), "_v", "_v", op) for n, op in ((0, "="), (1, ">"), (2, "<"))]
    else:
        s, t, bits = ranks.codes(s, t, a, b, staging, tag)
        if path:
            ends = _ends(s, t, pred, path)
        pieces.append((s, t, a, b, p.op.rstrip("=") if p.op in ("<=", ">=") else p.op))
        if p.op in ("<=", ">="):  # equal codes meet in a level of their own
            pieces.append((s, t, a, b, "="))
    parts_s, parts_t = [], []
    for left, right, x, y, op in pieces:
        for low, width in [(-1, 0)] if op == "=" else _segments(bits):
            for df, c, out in ((left, x, parts_s), (right, y, parts_t)):
                code = F.col(c)
                prefix = code if op == "=" else F.shiftright(code, low + width)
                if op == "=" and p.op == "band":
                    prefix = F.lit(0)
                digit = F.lit(0) if op == "=" else F.shiftright(code, low).bitwiseAND(F.lit((1 << width) - 1))
                level = F.struct("_g", F.array(*[F.col(n) for n in path]).alias("path") if path else F.lit(None).cast("array<struct<h:int,p:bigint>>").alias("path"), F.lit(op).alias("op"), F.lit(low).alias("low"), prefix.cast("long").alias("prefix"))
                out.append(df.select("rid", F.to_json(level).alias("level"), F.lit(op).alias("op"), digit.cast("long").alias("digit")))
    e_s, e_t = (reduce(DataFrame.unionByName, x) for x in (parts_s, parts_t))
    x, y = e_s.select("level", "op", "digit").distinct(), e_t.select("level", F.col("digit").alias("digit_t")).distinct()
    d, e = F.col("digit"), F.col("digit_t")
    # per level and prefix the digits on a side are at most the square root of the values below it
    mid = x.join(merged(y), "level").where(F.when(F.col("op") == "<", d < e).when(F.col("op") == ">", d > e).when(F.col("op") == "!=", d != e).otherwise(d == e))
    node = lambda side, digit: F.struct(F.lit(side).alias("side"), F.col("level"), F.col(digit).alias("digit"))
    mid = mid.select(node(0, "digit").alias("node_x"), node(1, "digit_t").alias("node_y"))
    e_in, e_out = e_s.select(F.col("rid").alias("rid_s"), node(0, "digit").alias("node_x")), e_t.select(node(1, "digit").alias("node_y"), F.col("rid").alias("rid_t"))
    e_in = e_in.join(merged(mid.select("node_x").distinct()), "node_x", "left_semi").select("rid_s", "node_x")
    e_out = e_out.join(merged(mid.select("node_y").distinct()), "node_y", "left_semi").select("node_y", "rid_t")
    return Connector([e_in, mid, e_out], 3, 1, ends=ends)


def chain(s: DataFrame, t: DataFrame, pred: tuple[Compare, str, str], staging: Staging, tag: str = "chain") -> Connector:
    """Nested ranges for one inequality: a node per distinct target value, each linked to the next.

    Sources point to the first target value that fits, every value node to its targets and
    to the next value node. Linear in size, but a path may cross all nodes, so it is
    used for its size and order, and windows take its place in the dynamic program. Nodes
    are the values' dense ranks, and the first one that fits is a fold.
    """
    from . import fold

    p, a, b = pred
    s, t = _keys(s, "rid", [(a, a)]), _keys(t, "rid", [(b, b)])
    up = p.op in ("<", "<=")
    values, _ = ranks.dense_rank_domain(t, b, staging, tag)
    values = values.select("val", (F.col("rk") if up else -F.col("rk")).alias("node"))
    fits = fold.fold(s, values.select(F.col("val").alias(b), F.col("node").alias("val")), [[(p, a, b)]], "min", "node", staging, f"{tag}-first")
    e_mid = values.select("node").join(values.select((F.col("node") - 1).alias("node"), F.col("node").alias("node_next")), "node")
    e_out = t.join(merged(values), F.col(b) == F.col("val")).select("node", F.col("rid").alias("rid_t"))
    return Connector([fits.select(F.col("rid").alias("rid_s"), "node"), e_mid, e_out], -1, 1, layered=False)


def two_way(s: DataFrame, terms: list[list[tuple]]) -> tuple[DataFrame, list[list[tuple]]]:
    """Non-equalities as < or >, bands as two inequalities with shifted columns of ``s``."""
    out = []
    for term in terms:
        made: list[list[tuple]] = [[]]
        for p, a, b in term:
            if p.op == "!=":
                made = [[*m, (Compare(op, p.left, p.right), a, b)] for m in made for op in ("<", ">")]
            elif p.op == "band":
                low, high = f"{a}_low_{p.eps}", f"{a}_high_{p.eps}"
                s = s.withColumns({low: F.col(a) - F.lit(p.eps), high: F.col(a) + F.lit(p.eps)})
                made = [[*m, (Compare("<", p.left, p.right), low, b), (Compare(">", p.left, p.right), high, b)] for m in made]
            else:
                made = [[*m, (p, a, b)] for m in made]
        out += made
    return s, out


#: Comparisons of one pair of columns that never hold together.
_APART = {("<", ">"), ("<", ">="), ("<", "="), ("<=", ">"), (">", "="), ("=", "!=")}


def exclusive(terms: list[list[tuple]]) -> bool:
    """Whether any two terms have comparisons of the same columns that never hold together, so that a pair meets one term at most."""

    def apart(one: list[tuple], other: list[tuple]) -> bool:
        return any((a, b) == (x, y) and ((p.op, q.op) in _APART or (q.op, p.op) in _APART) for p, a, b in one for q, x, y in other)

    return all(apart(one, other) for n, one in enumerate(terms) for other in terms[:n])


def direct(s: DataFrame, t: DataFrame, terms: list[list[tuple]]) -> Connector:
    """One edge per joining pair; the naive connector, and the only one for opaque predicates.

    An opaque predicate comes with the aliases of s and t in place of key columns.
    """
    from .ranked import key_name

    left = s.select(F.col("rid").alias("rid_s"), *[F.col(c).alias(f"s_{c}") for c in s.columns if c != "rid"])
    right = t.select(F.col("rid").alias("rid_t"), *[F.col(c).alias(f"t_{c}") for c in t.columns if c != "rid"])
    cond = None
    for term in terms:
        one = None
        for p, a, b in term:
            c = F.expr(p.over(lambda x, a=a: f"{'s' if x.alias == a else 't'}_{key_name(x)}")) if isinstance(p, Opaque) else to_column(p, F.col(f"s_{a}"), F.col(f"t_{b}"))
            one = c if one is None else one & c
        one = F.lit(True) if one is None else one
        cond = one if cond is None else cond | one
    return Connector([left.join(right, cond).select("rid_s", "rid_t")], 1, 1)


def build(s: DataFrame, t: DataFrame, terms: list[list[tuple[Compare, str, str]]], method: str = "auto", tag: str = "edge") -> Connector:
    """Connector between S and T (each with ``rid`` and key columns) for a DNF of comparisons.

    ``auto``: multiway for a single comparison, binary split otherwise. ``multiway`` treats
    the last comparison of each term so and those before by binary splits. ``two-way`` has
    non-equalities and bands made of inequalities.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    if method == "auto" and any(isinstance(p, Opaque) for term in terms for p, _, _ in term):
        method = "direct"
    if method == "direct":
        return direct(s, t, terms)
    if any(isinstance(p, Opaque) for term in terms for p, _, _ in term):
        raise ValueError("opaque predicates need the direct connector")
    staging = Staging(s.sparkSession, "ranks")
    hard = [[p for p, _, _ in term if p.op != "="] for term in terms]
    if method == "chain":
        if len(terms) != 1 or len(hard[0]) != 1 or len(terms[0]) != 1 or hard[0][0].op not in ("<", "<=", ">", ">="):
            raise ValueError("a chain needs a single inequality")
        return chain(s, t, terms[0][0], staging, tag)
    if method == "two-way":
        s, terms = two_way(s, terms)
        method, hard = "binary", [[p for p, _, _ in term if p.op != "="] for term in terms]
    made = []
    for k, term in enumerate(terms):
        how = method if method != "auto" else ("multiway" if len(hard[k]) == 1 and hard[k][0].op != "band" else "binary")
        how = "binary" if how == "multiway" and not hard[k] else how
        made.append(_term(s, t, term, staging, f"{tag}-{k}", how))
    if len(made) == 1:
        return made[0]
    if len({len(c.parts) for c in made}) > 1:  # terms of mixed depth are reduced one by one
        made = [_term(s, t, term, staging, f"{tag}-{k}-b", "binary") for k, term in enumerate(terms)]
    parts = []
    for j in range(len(made[0].parts)):
        tagged = []
        for k, c in enumerate(made):
            p = c.parts[j]
            tagged.append(p.select(*[F.struct(F.lit(k).alias("term"), F.col(x).alias("node")).alias(x) if not x.startswith("rid") else F.col(x) for x in p.columns]))
        if len({str(x.schema) for x in tagged}) > 1:  # paths of different make are compared as text
            tagged = [p.select(*[F.to_json(F.col(x)).alias(x) if not x.startswith("rid") else F.col(x) for x in p.columns]) for p in tagged]
        one = tagged[0]
        for p in tagged[1:]:
            one = one.unionByName(p)
        parts.append(one)
    return Connector(parts, max(c.depth for c in made), 1 if exclusive(terms) else len(made), terms=made if any(c.ends for c in made) else [])
