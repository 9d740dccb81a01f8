"""Benchmark decontamination by containment sketches in size classes.

An item is contained in a document if at least ``threshold`` of its distinct shingles of
five words are among the document's. Items are dealt into classes by size (powers of
two), each with an index of its own that documents with too few shingles for any of its
items pass by. Within a class each item is sketched by its smallest shingle hashes, as many as
make it certain that a document with enough of the item has one of them: hi - ceil(t *
hi) + 1 for a class up to hi shingles. This is the MinHash containment search in which
the small side is sketched and the large side is probed as a whole, so that a short item
inside a long document needs no more hashes than elsewhere, and nothing is missed. Each
candidate is then verified on the full sets.

Items go round in blocks of a fixed number of shingles, one broadcast and one pass over
the documents for each, so that memory is bounded for a benchmark of any size.

Nulls: a null text is empty; an item or document without words is linked with nothing;
a null id is carried. An item or document of one to four words has its whole sequence as
one shingle. Repeated rows: each row of documents is reported with each distinct item
row. Columns beyond ids and texts are ignored by ``leaks`` and carried by ``clean``. Empty
tables: no leaks, all rows clean.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import textkit
from .workspace import Workspace

#: Shingles of all items of one block.
BLOCK_SHINGLES = 1 << 21
_FIELDS = [("doc_id", pa.int64()), ("item_id", pa.int64()), ("n_item", pa.int64()), ("n_shared", pa.int64()), ("containment", pa.float64())]


def needed(n: int, threshold: float) -> int:
    """Shared shingles that an item of n must have; counted in hundredths, so that 0.75 is exact."""
    return -(-n * round(threshold * 100) // 100)


def size_class(n: int) -> int:
    """The power of two that an item of n shingles is counted under."""
    return max(0, math.ceil(math.log2(max(1, n))))


def sketch(hashes: np.ndarray, threshold: float) -> np.ndarray:
    """The smallest hashes of a sorted set: one of them is in each set that contains enough of it."""
    hi = 1 << size_class(len(hashes))
    return hashes[: max(1, min(len(hashes), hi - needed(hi, threshold) + 1))]


class SizeClass:
    """The sketches of the items of one size class, by hash."""

    def __init__(self, members: list[int], items: list[tuple[int | None, np.ndarray]], threshold: float):
        sketches = [sketch(items[i][1], threshold) for i in members]
        keys = np.concatenate(sketches)
        order = np.argsort(keys, kind="stable")
        self.keys, self.owner = keys[order], np.repeat(np.array(members, np.int64), [len(s) for s in sketches])[order]
        #: A set with fewer shingles holds no item of the class.
        self.least = min(needed(len(items[i][1]), threshold) for i in members)

    def candidates(self, sh: np.ndarray, at: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(text, item) for each of the shingles ``at`` that is in a sketch."""
        large = np.diff(bounds) >= self.least
        text = np.searchsorted(bounds, at, "right") - 1
        at, text = at[large[text]], text[large[text]]
        first, last = np.searchsorted(self.keys, sh[at], "left"), np.searchsorted(self.keys, sh[at], "right")
        hit = last > first
        first, text = first[hit], text[hit]
        count = (last[hit] - first).astype(np.int64)
        return np.repeat(text, count), self.owner[np.repeat(first, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)]


class Index:
    """One index of sketches for each size class of a block of items, probed with the shingles of many documents."""

    def __init__(self, items: list[tuple[int | None, np.ndarray]], threshold: float):
        self.items, self.threshold = items, threshold
        members: dict[int, list[int]] = {}
        for i, (_, s) in enumerate(items):
            members.setdefault(size_class(len(s)), []).append(i)
        self.classes = [SizeClass(m, items, threshold) for _, m in sorted(members.items())]
        self.coarse = np.zeros(1 << 22, bool)
        for c in self.classes:
            self.coarse[c.keys >> np.uint64(42)] = True

    def probe(self, sh: np.ndarray, bounds: np.ndarray):
        """Yields (text, item, shared) for each contained item."""
        at = np.flatnonzero(self.coarse[sh >> np.uint64(42)])
        if not self.classes or not len(at):
            return
        text, item = (np.concatenate(x) for x in zip(*[c.candidates(sh, at, bounds) for c in self.classes], strict=True))
        pairs = np.unique(text * len(self.items) + item)
        held, own = -1, None
        for t, i in zip((pairs // len(self.items)).tolist(), (pairs % len(self.items)).tolist(), strict=True):
            if t != held:
                held, own = t, textkit.distinct(sh[bounds[t] : bounds[t + 1]])
            mine = self.items[i][1]
            place = np.minimum(np.searchsorted(own, mine), len(own) - 1)
            shared = int((own[place] == mine).sum())
            if shared >= needed(len(mine), self.threshold):
                yield t, i, shared


def _item_sets(items: DataFrame) -> DataFrame:
    def sets(batches):
        for batch in batches:
            found = list(textkit.shingle_sets(batch.column(1)))
            yield pa.RecordBatch.from_pydict({"item_id": batch.column(0), "n": [len(s) for s in found], "hashes": [s.tobytes() for s in found]}, schema=pa.schema([("item_id", pa.int64()), ("n", pa.int64()), ("hashes", pa.binary())]))

    return items.select("item_id", "text").distinct().mapInArrow(textkit.frugal(sets), "item_id long, n long, hashes binary").where("n > 0")


def _indexes(items: DataFrame, work: Workspace) -> Iterator:
    """A broadcast list of (item_id, hashes) for each block of items."""
    spark = items.sparkSession
    running = Window.orderBy("item_id", "hashes").rowsBetween(Window.unboundedPreceding, 0)
    held = work.save(_item_sets(items).withColumn("block", F.floor((F.sum("n").over(running) - F.col("n")) / BLOCK_SHINGLES)), "items")
    for (block,) in held.select("block").distinct().orderBy("block").collect():
        rows = held.where(F.col("block") == block).orderBy("item_id", "hashes").collect()  # BLOCK_SHINGLES and one item at most
        yield spark.sparkContext.broadcast([(r["item_id"], bytes(r["hashes"])) for r in rows])


def leaks(docs: DataFrame, items: DataFrame, threshold: float = 0.75) -> DataFrame:
    """doc_id, item_id, n_item, n_shared, containment for each item that a document contains."""
    found = None
    for index in _indexes(items, Workspace(docs.sparkSession, "leaks")):
        part = docs.select("doc_id", "text").mapInArrow(textkit.frugal(_prober(index, threshold)), "doc_id long, item_id long, n_item long, n_shared long, containment double")
        found = part if found is None else found.unionByName(part)
    return docs.sparkSession.createDataFrame([], "doc_id long, item_id long, n_item long, n_shared long, containment double") if found is None else found


def _index(shared, threshold: float) -> Index:
    return Index([(i, np.frombuffer(h, np.uint64)) for i, h in shared.value], threshold)


def _prober(shared, threshold: float):
    def probe(batches):
        index = _index(shared, threshold)
        for batch in batches:
            at, out = 0, {name: [] for name, _ in _FIELDS}
            for part in textkit.slices(batch.column(1)):
                for t, i, n in index.probe(*textkit.shingles(*textkit.words(*textkit.utf8(part)))):
                    item, mine = index.items[i]
                    for name, value in zip(out, (batch.column(0)[at + t].as_py(), item, len(mine), n, n / len(mine)), strict=True):
                        out[name].append(value)
                at += len(part)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema(_FIELDS))

    return probe


def clean(docs: DataFrame, items: DataFrame, threshold: float = 0.75) -> DataFrame:
    """The rows of ``docs`` that contain no item, all columns unchanged.

    Each row is judged where it is read, by its own text, so that nothing is joined and
    rows without or with equal doc_id don't share their fate.
    """
    place = docs.columns.index("text")
    for index in _indexes(items, Workspace(docs.sparkSession, "leaks")):
        docs = docs.mapInArrow(textkit.frugal(_sieve(index, threshold, place)), docs.schema)
    return docs


def _sieve(shared, threshold: float, place: int):
    def keep(batches):
        index = _index(shared, threshold)
        for batch in batches:
            at, good = 0, np.ones(batch.num_rows, bool)
            for part in textkit.slices(batch.column(place)):
                good[[at + t for t, _, _ in index.probe(*textkit.shingles(*textkit.words(*textkit.utf8(part))))]] = False
                at += len(part)
            yield batch.filter(pa.array(good))

    return keep


_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_SHINGLES = "list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END)"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+')"
#: DuckDB for ``leaks`` with the default threshold.
ORACLE = f"""
WITH i AS (SELECT item_id, {_SHINGLES} AS s FROM (SELECT DISTINCT item_id, text, {_WORDS} AS w FROM benchmark)),
d AS (SELECT doc_id, {_SHINGLES} AS s, row_number() OVER () AS r FROM (SELECT doc_id, {_WORDS} AS w FROM documents)),
iu AS (SELECT item_id, len(s) AS n, unnest(s) AS x FROM i), du AS (SELECT doc_id, r, unnest(s) AS x FROM d)
SELECT doc_id, item_id, n::BIGINT AS n_item, count(*)::BIGINT AS n_shared, count(*)::DOUBLE / n AS containment
FROM iu JOIN du USING (x) GROUP BY doc_id, r, item_id, n HAVING 100 * count(*) >= 75 * n
"""
