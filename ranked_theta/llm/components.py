"""Connected components by alternating star contractions on DataFrames, and in one task for few edges."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit
from .workspace import Workspace

#: Edges that one task contracts; beyond it they stay dealt out. Costs only, same results.
FEW = 1 << 20


def _mark(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
    return row["n"], row["h"]


def contract(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, component) of the edges: roots go below smaller ones, and all trees are made flat, until no edge joins two roots."""
    nodes, place = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = place[: len(a)], place[len(a) :]
    root = np.arange(len(nodes))
    while (root[x] != root[y]).any():
        np.minimum.at(root, np.maximum(root[x], root[y]), np.minimum(root[x], root[y]))
        while ((above := root[root]) != root).any():
            root = above
    return nodes, nodes[root]


def _in_one_task(edges: DataFrame) -> DataFrame:
    schema = pa.schema([("node", pa.int64()), ("component", pa.int64())])

    def read(batches):
        held = [np.stack([batch.column(k).to_numpy() for k in range(2)]) for batch in batches]
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in contract(*np.concatenate(held, axis=1))], schema=schema)

    return edges.select("a", "b").coalesce(1).mapInArrow(textkit.frugal(read), "node long, component long")


def components(edges: DataFrame, work: Workspace, name: str = "cc") -> DataFrame:
    """(a, b) -> (node, component): the smallest node reachable, for each node that has a link.

    Large star: every node's larger neighbours are linked to its smallest one; small
    star: its smaller neighbours are. Both keep the components and make the trees flat
    in a logarithmic number of rounds in practice. Minima are pre-aggregated and joins
    have one row per node on one side, so a node with very many links is split by the
    join and never gathered. Each round is a written table: a lost executor costs its
    tasks only, and no round repeats the ones before. ``edges`` are read twice, so they
    should be a written table; up to ``FEW`` of them need no rounds.
    """
    edges = edges.where("a <> b")
    if edges.count() <= FEW:
        return work.save(_in_one_task(edges), f"{name}0")
    now = work.save(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"{name}0")
    mark, turn = _mark(now), 0
    while mark[0]:
        turn += 1
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        large = work.save(large, f"{name}{turn}-large")
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b"))).distinct()
        after = work.save(small, f"{name}{turn}")
        work.drop(f"{name}{turn}-large")
        before, mark = mark, _mark(after)
        work.drop(f"{name}{turn - 1}")
        now = after
        if mark == before:
            break
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
