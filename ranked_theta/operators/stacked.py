"""The stacked graph: connectors of all edges between the atoms of a plan tree, and the walk through it.

1. ``stack`` builds a connector for each edge of the tree, by the method asked for.
2. The bottom-up pass sends the least completion from targets over nodes to sources, one
   aggregation for each layer of edges; the top-down pass sends what lies outside back.
   Where k is known beforehand, folds over the whole relations find the same k rows of
   each atom without edges, and only these rows are stacked.
3. The k rows of each atom in the best answers, and the edges and nodes between them,
   are the instance that an any-k enumerator walks on one machine. A hop from a row to a
   node is a choice of its own, so that the list of a node's targets is kept once for
   all rows that reach it.

The passes are joins and aggregations on ids; what is collected is at most k rows and
their levels for each atom. Terms of a disjunction can bring an answer several times;
``dedupe`` drops the repetitions.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.predicates import Opaque
from ..plans.query import Query
from . import anyk, connectors
from .joins import merged
from .ranked import Passes, _passes, edge_terms


@dataclass
class Stacked:
    """Passes whose edges are connectors; ``edges``: written edge relations by tree edge; ``k``: for how many answers rows were cut before."""

    passes: Passes
    edges: dict[tuple[str, str], connectors.Connector]
    k: int | None = None

    @property
    def duplicates(self) -> int:
        """How often an answer can come at most."""
        out = 1
        for c in self.edges.values():
            out *= c.dup_factor
        return out

    def size(self) -> DataFrame:
        """(nodes, edges) of all connectors together."""
        total = None
        for c in self.edges.values():
            total = c.size() if total is None else total.unionByName(c.size())
        return total.agg(F.sum("nodes").cast("long").alias("nodes"), F.sum("edges").cast("long").alias("edges"))


def _folds(passes: Passes) -> bool:
    """Whether folds can cut the rows: not on opaque predicates, nor where a better part need not make a better whole."""
    terms = [t for c in passes.tree.conditions.values() for t in c]
    return passes.query.rank.name in ("sum", "product") and not any(isinstance(p, Opaque) for t in terms for p in t)


def stack(query: Query, method: str = "auto", root: str | None = None, k: int | None = None) -> Stacked:
    """Connectors of all edges of an acyclic query; with ``k``, of the rows that can occur in the k best answers."""
    passes = _passes(query, root)
    if k is not None and k > 0 and _folds(passes):
        passes.cut(k)
    else:
        k = None
    edges = {}
    for parent, child in passes.tree.conditions:
        left, right = ((passes.rows(a) if k is None else passes.reduced[a]).select("rid", *passes.keys(a)) for a in (parent, child))
        made = connectors.build(left, right, edge_terms(passes.tree, parent, child), method, f"{parent}-{child}")
        if not made.layered:
            raise ValueError("a chain has no layers to stack; it serves to compare sizes")
        made.parts = [passes.staging.save(p, f"edge-{parent}-{child}-{k}") for k, p in enumerate(made.parts)]
        edges[parent, child] = made
    return Stacked(passes, edges, k)


def _hop(values: DataFrame, edges: DataFrame, back: bool) -> DataFrame:
    """(id, val): the least value over a layer of edges, from its right side to its left one or (``back``) the other way."""
    near, far = edges.columns if back else reversed(edges.columns)
    return edges.join(merged(values.withColumnRenamed("id", near)), near).groupBy(F.col(far).alias("id")).agg(F.min("val").alias("val"))


def bottom_up(g: Stacked) -> None:
    """Fills ``passes.up``: rows with a completion, its least value ``pi`` and the children's shares."""
    p = g.passes
    for alias in reversed(p.tree.preorder()):
        rows, parts = p.rows(alias), []
        for child in p.tree.children[alias]:
            values = p.up[child].select(F.col("rid").alias("id"), F.col("pi").alias("val"))
            for layer in reversed(g.edges[alias, child].parts):
                values = _hop(values, layer, False)
            rows = rows.join(merged(values.select(F.col("id").alias("rid"), F.col("val").alias(f"m_{child}"))), "rid")
            parts.append((p.tree.subtree(child), F.col(f"m_{child}")))
        p.up[alias] = p.staging.save(rows.withColumn("pi", p.value([p.own(alias)], parts)), f"stacked-up-{alias}")


def cut(g: Stacked, k: int) -> None:
    """Fills ``passes.reduced``: each atom's rows that can occur in the k best answers."""
    p = g.passes
    tree, everyone = p.tree, set(range(len(p.query.atoms)))
    p.reduced[tree.root] = p.staging.save(p.up[tree.root].orderBy("pi").limit(k), f"stacked-{k}-{tree.root}")
    outside = {tree.root: None}
    for alias in tree.preorder():
        for child in tree.children[alias]:
            rest = [(tree.subtree(c), F.col(f"m_{c}")) for c in tree.children[alias] if c != child]
            if outside[alias] is not None:
                rest.append((sorted(everyone - set(tree.subtree(alias))), F.col("up")))
            values = p.reduced[alias].select(F.col("rid").alias("id"), p.value([p.own(alias)], rest).alias("val"))
            for layer in g.edges[alias, child].parts:
                values = _hop(values, layer, True)
            kept = p.up[child].join(merged(values.select(F.col("id").alias("rid"), F.col("val").alias("up"))), "rid")
            inside = tree.subtree(child)
            through = p.value([], [(inside, F.col("pi")), (sorted(everyone - set(inside)), F.col("up"))])
            p.reduced[child] = p.staging.save(kept.withColumn("thru", through).orderBy("thru").limit(k).drop("thru"), f"stacked-{k}-{child}")
            outside[child] = F.col("up")


def _between(layers: list[DataFrame], above: DataFrame, below: DataFrame) -> list[DataFrame]:
    """The edges on paths from rows of ``above`` to rows of ``below``."""
    layers = [*layers]
    first, last = layers[0].columns[0], layers[-1].columns[-1]
    layers[0] = layers[0].join(above.select(F.col("rid").alias(first)), first, "left_semi").select(*layers[0].columns)
    layers[-1] = layers[-1].join(below.select(F.col("rid").alias(last)), last, "left_semi").select(*layers[-1].columns)
    for n in range(len(layers) - 1):  # edges into nodes that lead on, and out of nodes that are reached
        a, b = layers[n].columns[-1], layers[n + 1].columns[0]
        layers[n + 1] = layers[n + 1].join(layers[n].select(F.col(a).alias(b)).distinct(), b, "left_semi").select(*layers[n + 1].columns)
    for n in reversed(range(len(layers) - 1)):
        a, b = layers[n].columns[-1], layers[n + 1].columns[0]
        layers[n] = layers[n].join(layers[n + 1].select(F.col(b).alias(a)).distinct(), a, "left_semi").select(*layers[n].columns)
    return layers


def instance(g: Stacked, k: int) -> anyk.Instance:
    """The reduced graph for the k best answers, on this machine: at most k rows of each atom and the edges between them."""
    if g.k is None:
        if not g.passes.up:
            bottom_up(g)
        cut(g, k)
    elif g.k < k:
        raise ValueError(f"the rows were cut for {g.k} answers")
    p = g.passes
    parents, rows, joins, nodes, order = [], [], [], [], []

    def add(parent: int | None, made: list[tuple], slot: int | None) -> int:
        parents.append(parent)
        rows.append(made)
        joins.append({})
        nodes.append({})
        order.append(slot)
        return len(rows) - 1

    held: dict[str, tuple[int, dict]] = {}  # place of an atom, and of its rows by id
    for alias in p.tree.preorder():
        found = p.reduced[alias].select("rid", "w").orderBy("rid").collect()  # k rows
        made = [(r["w"], r["rid"]) for r in found]
        parent = p.tree.parent(alias)
        if parent is None:
            held[alias] = add(None, made, p.query.index(alias)), {r["rid"]: n for n, r in enumerate(found)}
            continue
        graph = g.edges[parent, alias]
        layers = [*graph.parts]
        if g.k is None:  # else only rows that were kept have edges, and the walk leaves out nodes that lead nowhere
            layers = _between(layers, p.reduced[parent], p.reduced[alias])
        at, places = held[parent]
        for n, layer in enumerate(layers):
            # nodes as text, so that they can be looked up
            plain = [F.col(c) if c.startswith("rid") else F.to_json(c).alias(c) for c in layer.columns]
            pairs = [tuple(r) for r in layer.select(*plain).collect()]  # k rows by their levels
            end = n == len(layers) - 1
            if end:
                into = {r["rid"]: i for i, r in enumerate(found)}
                here = add(at, made, p.query.index(alias))
            else:
                names = list(dict.fromkeys(y for _, y in pairs))
                into = {y: i for i, y in enumerate(names)}
                here = add(at, [(None, None)] * len(names), None)
            lists: dict[int, list[int]] = {}
            for x, y in pairs:
                if x in places and y in into:
                    lists.setdefault(places[x], []).append(into[y])
            joins[here] = {x: x for x in lists}
            nodes[here] = lists
            at, places = here, into
        held[alias] = at, places
    return anyk.Instance(parents, rows, joins, nodes, order, p.query.rank)


def dedupe(found: Iterable[tuple]) -> Iterator[tuple]:
    """A ranked stream without repeated answers; only the answers of the current weight are remembered."""
    weight, seen = None, set()
    for w, ids in found:
        if w != weight:
            weight, seen = w, set()
        if ids not in seen:
            seen.add(ids)
            yield w, ids


def walk(g: Stacked, k: int, variant: str = "lazy", stamps: list | None = None, cost: anyk.Cost | None = None) -> Iterator[tuple]:
    """(weight, ids) of the k best answers in order."""
    found = anyk.enumerate_answers(instance(g, k), variant, stamps, cost)
    if g.duplicates > 1:
        found = dedupe(found)
    for n, one in enumerate(found, 1):
        if n > k:
            return
        yield one


def any_k(query: Query, k: int, variant: str = "lazy", method: str = "auto", root: str | None = None) -> DataFrame:
    """rank, weight, rid_1.. of the k best answers, by the walk through the stacked graph."""
    g = stack(query, method, root, k)
    p = g.passes
    n = range(len(p.query.atoms))
    rows = [(i, w, *ids) for i, (w, ids) in enumerate(walk(g, k, variant), 1)]  # k rows
    kinds = {a.alias: dict(p.rows(a.alias).dtypes) for a in p.query.atoms}
    weight = "decimal(38,0)" if p.query.rank.name == "product" else kinds[p.query.atoms[0].alias]["w"]
    schema = ", ".join(["rank long", f"weight {weight}", *[f"rid_{i + 1} {kinds[p.query.atoms[i].alias]['rid']}" for i in n]])
    found = query.atoms[0].df.sparkSession.createDataFrame(rows, schema)
    found = found.withColumn("weight", p.query.rank.shown(F.col("weight")))
    return p.name_rows(found, {f"rid_{i + 1}": p.query.atoms[i].alias for i in n}, k)
