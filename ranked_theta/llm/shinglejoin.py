"""N-gram Jaccard join with count-vector R-trees.

Documents are sets of hashed five-word shingles; two link when 100 * intersection >= 75
* union. Equal sets form a class, named by a digest, and only classes are joined.

Distribution. All shingles have one global order: by how often their bucket of a fixed
count sketch over all documents occurs, then by hash. Two classes that link share one of
the first n - ceil(0.75 n) + 1 shingles of each in that order, so classes are routed by
these and passages that many documents share are not among them unless a document
consists of little else.

Join. Shingle hashes are dealt into ``DIMENSIONS`` token groups, and a class is the point
of its counts per group. The sum of coordinate minima bounds the intersection from above.
First each routed class is tried with a few centres of the groups of its routing keys,
those that most of its keys have, which is linear; what links becomes a component. A second
round does the same between components with centres in a random order. Then each routing
key's classes that are still in different components go into an R-tree over their points:
a node holds the largest counts and the range of set sizes below it, and a search leaves
out nodes and points whose bound can't reach the overlap. A pair comes up under every key
that it shares; each class carries its ``HEAD`` smallest keys, and a pair that shares some
of these is reported under the smallest of them only. Pairs that survive are verified on
the exact sets. Classes already in one component are not compared again, so a dense group
of near copies costs no quadratic number of pairs, and no link between components is lost:
the centres only save work, and whatever they leave open the search compares.

Nulls: a null text or one without words has an empty set and links with nothing; one to
four words are one shingle; a null doc_id takes part in links, and a component of null
ids alone has component null. Repeated rows have equal sets and are one class. Empty
table: empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from . import columns, groups, partials, textkit
from .components import components
from .workspace import Workspace

#: Buckets of the count sketch, token groups of a point, entries of an R-tree node.
SKETCH, DIMENSIONS, FANOUT = 1 << 18, 256, 16
#: Largest count that a point holds; a point with such a count rules nothing out.
MOST = 255
#: Smallest routing keys that a class carries, and what stands for none.
HEAD, NO_KEY = 8, -(2**63)
#: Centres that a class is tried with in each round before the search; orders of centres in the second.
CENTRES, ORDERS = (3, 8), 16
#: Classes of one routing key that are joined at once.
BLOCK = 4096
#: Bits of the map of wanted texts; members of a group that is compared with others as a whole.
MARKS, SMALL = 1 << 24, 64
_U = np.uint64


def bucket(h: np.ndarray) -> np.ndarray:
    return (h >> _U(46)).astype(np.int64)


def overlap_needed(a, b, percent: int = 75):
    """The least intersection with 100 * i >= percent * (a + b - i)."""
    return -(-percent * (a + b) // (100 + percent))


def prefix_length(n: int, percent: int = 75) -> int:
    return n - -(-percent * n // 100) + 1


def point(hashes: np.ndarray) -> np.ndarray:
    """Counts per token group; the groups are taken from other bits than the sketch."""
    return np.minimum(np.bincount((hashes & _U(DIMENSIONS - 1)).astype(np.int64), minlength=DIMENSIONS), MOST).astype("u1")


def points_of(raw: list[bytes]) -> np.ndarray:
    """A row for each point; one that holds ``MOST`` is made to rule nothing out."""
    out = np.frombuffer(b"".join(raw), "u1").reshape(-1, DIMENSIONS).astype(np.int32)
    full = (out == MOST).any(1)
    if full.any():
        out[full] = 1 << 22
    return out


def class_name(hashes: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(hashes.tobytes(), digest_size=8).digest(), "big", signed=True)


class CountTree:
    """An R-tree over count vectors, packed by size and then by coordinate.

    A level is arrays of largest counts and of least and largest set size per node; node
    i holds entries i * FANOUT to (i + 1) * FANOUT of the level below.
    """

    def __init__(self, points: np.ndarray, sizes: np.ndarray):
        self.order = np.lexsort((*points.T[:2], sizes))
        self.points, self.sizes = points[self.order], sizes[self.order]
        top, low, high = self.points, self.sizes, self.sizes
        self.levels = []
        while len(low) > FANOUT:
            cuts = np.arange(0, len(low), FANOUT)
            top, low, high = np.maximum.reduceat(top, cuts), np.minimum.reduceat(low, cuts), np.maximum.reduceat(high, cuts)
            self.levels.append((top, low, high))

    @staticmethod
    def _may(q, n, top, low, high, percent):
        fits = (100 * low <= 10_000 * n // percent) & (100 * high >= percent * n)
        bound = np.minimum(top, q).sum(1)
        return fits & (np.minimum(bound, np.minimum(high, n)) >= overlap_needed(n, np.maximum(low, -(-percent * n // 100)), percent))

    def search(self, q: np.ndarray, n: int, percent: int = 75) -> np.ndarray:
        """Rows whose overlap with a set of ``n`` at point ``q`` can reach the threshold."""
        at = np.arange(len(self.levels[-1][1]) if self.levels else len(self.sizes))
        for level in range(len(self.levels) - 1, -1, -1):
            top, low, high = (x[at] for x in self.levels[level])
            kept = at[self._may(q, n, top, low, high, percent)]
            below = len(self.levels[level - 1][1]) if level else len(self.sizes)
            at = (kept[:, None] * FANOUT + np.arange(FANOUT)).reshape(-1)
            at = at[at < below]
        fit = np.minimum(self.points[at], q).sum(1) >= overlap_needed(n, self.sizes[at], percent)
        return self.order[at[fit & (100 * np.minimum(self.sizes[at], n) >= percent * np.maximum(self.sizes[at], n))]]


def describe(docs: DataFrame, work: Workspace) -> tuple[DataFrame, np.ndarray]:
    """(doc_id, row, cls, n, point) of all rows, and the count sketch over all documents."""
    schema = pa.schema([("doc_id", pa.int64()), ("row", pa.int64()), ("cls", pa.int64()), ("n", pa.int64()), ("point", pa.binary()), ("piece", pa.int32()), ("salt", pa.int32()), ("part", pa.binary())])

    def read(batches):
        from pyspark import TaskContext

        total = np.zeros(SKETCH, np.int64)
        for batch in batches:
            at = 0
            for part in textkit.slices(batch.column(2), 1 << 21):
                sets = list(textkit.shingle_sets(part))
                total += np.bincount(bucket(np.concatenate(sets)), minlength=SKETCH) if sets else 0
                out = {"doc_id": batch.column(0).slice(at, len(part)), "row": batch.column(1).slice(at, len(part)), "cls": [class_name(s) for s in sets], "n": [len(s) for s in sets], "point": [point(s).tobytes() for s in sets]}
                yield pa.RecordBatch.from_pydict(out | {k: pa.nulls(len(sets), schema.field(k).type) for k in ("piece", "salt", "part")}, schema=schema)
                at += len(part)
        held = partials.rows(total, TaskContext.get().partitionId())
        yield pa.RecordBatch.from_pydict({k: pa.nulls(len(held["piece"]), schema.field(k).type) for k in ("doc_id", "row", "cls", "n", "point")} | held, schema=schema)

    rows = docs.select("doc_id", textkit.row_key(), "text").mapInArrow(textkit.frugal(read), f"doc_id long, row long, cls long, n long, point binary, {partials.SCHEMA}")
    rows = work.save(rows, "described")
    sketch = partials.collect(rows.where("piece is not null").select("piece", "salt", "part"), SKETCH)
    return rows.where("n is not null").select("doc_id", "row", "cls", "n", "point"), sketch


def routing_keys(docs: DataFrame, sketch: np.ndarray, percent: int) -> DataFrame:
    """(key, cls, n): the prefix shingles of each class, once per task."""
    shared = docs.sparkSession.sparkContext.broadcast(sketch)
    schema = pa.schema([("key", pa.int64()), ("cls", pa.int64()), ("n", pa.int32())])

    def route(batches):
        order, seen = shared.value, set()
        for batch in batches:
            for part in textkit.slices(batch.column(0), 1 << 21):
                keys, owner = [], []
                for s in textkit.shingle_sets(part):
                    name = class_name(s) if len(s) else None
                    if name is None or name in seen:
                        continue
                    seen.add(name)
                    m = prefix_length(len(s), percent)
                    rank = order[bucket(s)]
                    # sets are sorted by hash; a stable sort by count breaks ties by it
                    keys.append(s[np.argsort(rank, kind="stable")[:m]])
                    owner.append((name, len(s), m))
                if keys:
                    name, n, m = (np.array(x, np.int64) for x in zip(*owner, strict=True))
                    yield pa.RecordBatch.from_pydict({"key": textkit.signed(np.concatenate(keys)), "cls": np.repeat(name, m), "n": np.repeat(n, m).astype(np.int32)}, schema=schema)

    return docs.select("text").mapInArrow(textkit.frugal(route), "key long, cls long, n int")


def _only(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose ``row`` may be among ``rows``: a bitmap of fixed size, so that few other texts are shuffled."""
    mark = lambda c: F.pmod(F.xxhash64(c), F.lit(MARKS))
    word, bit = (lambda m: F.shiftright(m, 6)), (lambda m: F.call_function("shiftleft", F.lit(1).cast("long"), m.bitwiseAND(F.lit(63)).cast("int")))
    marks = rows.select(mark("row").alias("m")).groupBy(word(F.col("m")).alias("word")).agg(F.bit_or(bit(F.col("m"))).alias("bits"))
    marked = docs.withColumn("m", mark("row")).withColumn("word", word(F.col("m")))
    return marked.join(F.broadcast(marks), "word").where(F.col("bits").bitwiseAND(bit(F.col("m"))) != 0).drop("m", "word", "bits")  # MARKS / 64 rows at most


def verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, percent: int, work: Workspace, name: str, exact: bool = True) -> DataFrame:
    """The pairs (a, b) of classes whose exact sets link.

    Without ``exact``: the pairs that counts in 65,536 token groups don't rule out. Two
    bytes of each hash are shipped then, a quarter of the set.

    Pairs go to the texts they need, a text first and what is asked of it after it; then the
    sets of all a of one b go to where the set of b is. A b with very many a is dealt into
    parts, each with a copy of its set, and both steps read a stream, so that a task holds
    a text and two sets.
    """
    partitions = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    salts = pairs.groupBy("b").agg(F.ceil(F.count(F.lit(1)) / 512).alias("salts")).where("salts > 1")
    dealt = pairs.join(salts, "b", "left").withColumn("salt", F.pmod(F.xxhash64("a"), F.coalesce("salts", F.lit(1))))
    jobs = dealt.select(F.col("a").alias("cls"), F.col("b").alias("centre"), "salt", F.lit(1).alias("role")).unionByName(dealt.select(F.col("b").alias("cls"), F.col("b").alias("centre"), "salt", F.lit(0).alias("role")).distinct())
    jobs = work.save(jobs.join(classes.select("cls", "row"), "cls"), f"{name}-jobs")
    schema = pa.schema([("centre", pa.int64()), ("salt", pa.int64()), ("role", pa.int32()), ("cls", pa.int64()), ("hashes", pa.binary())])

    def sets(batches):
        row, known = None, {}
        for batch in batches:
            out, held, at = {n: [] for n in schema.names}, 0, 0
            for part in textkit.slices(batch.column(1), 1 << 21):
                jobs_ = [batch.column(k).slice(at, len(part)).to_pylist() for k in (0, 2, 3, 4, 5)]
                at += len(part)
                for r, c, centre, salt, role, hashes in zip(*jobs_, textkit.shingle_sets(part), strict=True):
                    if r != row:
                        row, known = r, {}
                    if c is None:  # a text; its jobs follow
                        known[class_name(hashes)] = (hashes if exact else hashes.astype("<u2")).tobytes()
                    elif c in known:
                        for n, v in zip(schema.names, (centre, salt, role, c, known[c]), strict=True):
                            out[n].append(v)
                        held += len(known[c])
                        if held > 1 << 23:
                            yield pa.RecordBatch.from_pydict(out, schema=schema)
                            out, held = {n: [] for n in schema.names}, 0
            yield pa.RecordBatch.from_pydict(out, schema=schema)

    texts = _only(docs, jobs).select("row", "text", *[F.lit(None).cast("long").alias(c) for c in ("cls", "centre", "salt")], F.lit(None).cast("int").alias("role"))
    asked = texts.unionByName(jobs.select("row", F.lit(None).cast("string").alias("text"), "cls", "centre", "salt", "role"))
    asked = asked.repartition(partitions, "row").sortWithinPartitions("row", F.col("cls").isNotNull())
    shipped = asked.mapInArrow(textkit.frugal(sets), "centre long, salt long, role int, cls long, hashes binary").repartition(partitions, "centre", "salt").sortWithinPartitions("centre", "salt", "role")

    def test(batches):
        held, own, counts = None, None, None
        for batch in batches:
            out = {"a": [], "b": []}
            centre, role, cls = (batch.column(k).to_pylist() for k in (0, 2, 3))
            for i in range(batch.num_rows):
                mine = np.frombuffer(batch.column(4)[i].as_buffer(), np.uint64 if exact else "<u2")
                if role[i] == 0:
                    held, own = centre[i], mine.copy()
                    counts = None if exact else np.bincount(own, minlength=1 << 16)
                elif held == centre[i]:
                    both = len(np.intersect1d(own, mine, assume_unique=True)) if exact else int(np.minimum(counts, np.bincount(mine, minlength=1 << 16)).sum())
                    if 100 * both >= percent * (len(own) + len(mine) - both):
                        out["a"].append(cls[i])
                        out["b"].append(held)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("a", pa.int64()), ("b", pa.int64())]))

    return shipped.mapInArrow(textkit.frugal(test), "a long, b long")


def bounded(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """The pairs that sizes and points don't rule out."""
    a = classes.select(F.col("cls").alias("a"), F.col("n").alias("na"), F.col("point").alias("pa"))
    b = classes.select(F.col("cls").alias("b"), F.col("n").alias("nb"), F.col("point").alias("pb"))

    def rule(batches):
        for batch in batches:
            na, nb = batch.column(2).to_numpy(), batch.column(3).to_numpy()
            ok = np.zeros(batch.num_rows, bool)
            for i in range(0, batch.num_rows, 1024):
                pa_, pb = (points_of(batch.column(k).slice(i, 1024).to_pylist()) for k in (4, 5))
                ok[i : i + 1024] = np.minimum(pa_, pb).sum(1) >= overlap_needed(na[i : i + 1024], nb[i : i + 1024], percent)
            ok = pa.array(ok)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(ok), batch.column(1).filter(ok)], names=["a", "b"])

    return pairs.join(a, "a").join(b, "b").where(_near("na", "nb", percent)).select("a", "b", "na", "nb", "pa", "pb").mapInArrow(textkit.frugal(rule), "a long, b long")


def star_pairs(rows: DataFrame, order, most: int, percent: int) -> DataFrame:
    """(a, b): each class with the ``most`` centres that the most of its keys have.

    ``rows``: key, cls, n, part; a key's centre is its class that comes last in ``order``.
    Pairs of one part, and of sizes that can't link, are left out.
    """
    centres = rows.groupBy("key").agg(F.max(F.struct(order.alias("by"), "cls", "part", "n")).alias("c"))
    pairs = rows.join(centres, "key").where((F.col("part") != F.col("c.part")) & _near("n", "c.n", percent)).groupBy(F.col("cls").alias("a"), F.col("c.cls").alias("b")).agg(F.count(F.lit(1)).alias("keys"))
    place = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("keys"), "b"))
    return pairs.withColumn("place", place).where(F.col("place") <= most).select("a", "b")


def _near(a: str, b: str, percent: int) -> Column:
    return 100 * F.least(a, b) >= percent * F.greatest(a, b)


def with_heads(rows: DataFrame, classes: DataFrame) -> DataFrame:
    """(cls, n, point, head0, ...) of the classes in ``rows`` (key, cls), with their smallest keys there."""
    heads = rows.groupBy("cls").agg(F.slice(F.sort_array(F.collect_list("key")), 1, HEAD).alias("head"))  # one set's keys
    return classes.join(heads, "cls").select("cls", "n", "point", *[F.coalesce(F.get("head", F.lit(i)), F.lit(NO_KEY)).alias(f"head{i}") for i in range(HEAD)])


def tree_pairs(rows: DataFrame, described: DataFrame, percent: int, partitions: int) -> DataFrame:
    """Pairs of one routing key and different components that an R-tree search finds.

    ``rows``: key, cls, part; ``described``: what ``with_heads`` has of each class. A key
    with more than ``BLOCK`` classes is dealt into blocks, and each pair of blocks is
    joined on its own.
    """
    blocks = F.ceil(F.count(F.lit(1)) / BLOCK).cast("long")
    large = rows.groupBy("key").agg(blocks.alias("blocks")).where("blocks > 1")
    rows = rows.join(large, "key", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long")))
    rows = rows.withColumn("own", F.pmod(F.xxhash64("cls"), F.col("blocks")))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    rows = rows.withColumn("pair", F.least("own", "other") * F.col("blocks") + F.greatest("own", "other")).withColumn("same", F.col("own") == F.col("other"))
    heads = [f"head{i}" for i in range(HEAD)]
    rows = rows.join(described, "cls").select("key", "pair", "cls", "part", "n", "point", "own", "same", *heads).repartition(partitions, "key", "pair").sortWithinPartitions("key", "pair", "cls")

    def search(batches):
        done: set[bytes] = set()
        for table, bounds in groups.runs(batches, 2):
            key, cls, part, n, own, same = (table.column(k).to_numpy() for k in ("key", "cls", "part", "n", "own", "same"))
            head = np.stack([table.column(k).to_numpy() for k in heads], axis=1)
            raw = table.column("point")
            left, right = [], []
            for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                name = hashlib.blake2b(cls[a:b].tobytes() + own[a:b].tobytes(), digest_size=16).digest()
                if b - a < 2 or name in done:  # keys of one passage have the same classes; the smallest came first
                    continue
                done.add(name)
                if len(done) > 200_000:
                    done.clear()
                points = points_of(raw.slice(int(a), int(b - a)).to_pylist())
                tree = CountTree(points, n[a:b])
                for i in range(b - a):
                    found = tree.search(points[i], int(n[a + i]), percent)
                    found = found[(cls[a + found] > cls[a + i]) & (part[a + found] != part[a + i])]
                    if not same[a]:
                        found = found[own[a + found] != own[a + i]]
                    if len(found):
                        found = found[reported_here(key[a], head[a + i], head[a + found])]
                    left.append(np.full(len(found), cls[a + i]))
                    right.append(cls[a + found])
            if left:
                yield pa.RecordBatch.from_pydict({"a": np.concatenate(left), "b": np.concatenate(right)}, schema=pa.schema([("a", pa.int64()), ("b", pa.int64())]))

    return rows.mapInArrow(textkit.frugal(search), "a long, b long")


def reported_here(key: int, head: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """Which of ``heads`` share no key with ``head``, or ``key`` as the smallest one."""
    shared = np.isin(heads, head[head != NO_KEY])
    first = np.where(shared, heads, np.iinfo(np.int64).max).min(1)
    return (first == key) | ~shared.any(1)


def join(docs: DataFrame, percent: int = 75) -> tuple[DataFrame, DataFrame, Workspace]:
    """(doc_id, cls, n) of all rows and (node, component) of the classes with links."""
    spark = docs.sparkSession
    work = Workspace(spark, "shinglejoin")
    partitions = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    described, sketch = describe(docs, work)
    # a class is read from the rows with one of its row keys
    classes = work.save(described.where("n > 0").groupBy("cls").agg(F.min("row").alias("row"), F.first("n").alias("n"), F.first("point").alias("point")), "classes")
    by_key = Window.partitionBy("key")
    keyed = routing_keys(docs, sketch, percent).withColumn("low", F.min("cls").over(by_key)).withColumn("high", F.max("cls").over(by_key))
    keyed = work.save(keyed.where("low <> high").select("key", "cls", "n").distinct().withColumn("size", F.count(F.lit(1)).over(by_key)), "keyed")
    source = textkit.by_row(docs)
    # what others were copied from shares most of its keys with most classes: it is the centre of its groups
    score = F.avg("size").over(Window.partitionBy("cls"))
    stars = star_pairs(keyed.select("key", "cls", "n", F.col("cls").alias("part"), score.alias("score")), F.col("score"), CENTRES[0], percent)
    tried = work.save(bounded(stars, classes, percent), "stars")
    linked = work.save(verified(tried, source, classes, percent, work, "linked"), "linked")
    rows = still_apart(keyed, components(linked, work, "first"), work, "apart")
    work.keep("described", "classes", "stars", "linked", "apart")
    stars = star_pairs(rows, F.xxhash64("cls", F.pmod("key", F.lit(ORDERS))), CENTRES[1], percent)
    again = work.save(bounded(_ordered(stars, tried), classes, percent), "stars-again")
    linked = work.save(linked.unionByName(verified(again, source, classes, percent, work, "again")), "linked-again")
    rows = still_apart(rows, components(linked, work, "second"), work, "apart-again")
    rows = work.save(distinct_groups(rows, Window.partitionBy("key")), "open")
    work.keep("described", "classes", "stars", "stars-again", "linked-again", "open")
    more = tree_pairs(rows, with_heads(rows, classes), percent, partitions)
    more = work.save(_ordered(more, tried.unionByName(again)), "more")
    more = work.save(verified(more, source, classes, percent, work, "fine", exact=False), "more-fine")
    more_linked = work.save(verified(more, source, classes, percent, work, "more"), "more-linked")
    parts = components(linked.unionByName(more_linked), work, "last")
    work.keep("described", *[name for name in work.names() if name.startswith("last")])
    return described, parts, work


def _ordered(pairs: DataFrame, tried: DataFrame) -> DataFrame:
    """Each pair once, without those that were tried."""
    once = lambda p: p.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    return once(pairs).distinct().join(once(tried), ["a", "b"], "left_anti")


def still_apart(rows: DataFrame, parts: DataFrame, work: Workspace, name: str) -> DataFrame:
    """(key, cls, part) of the keys with classes of more than one component."""
    by_key = Window.partitionBy("key")
    rows = rows.select("key", "cls", "n").join(parts.withColumnRenamed("node", "cls"), "cls", "left").select("key", "cls", "n", F.coalesce("component", "cls").alias("part"))
    rows = rows.withColumn("low", F.min("part").over(by_key)).withColumn("high", F.max("part").over(by_key)).where("low <> high")
    return work.save(rows.select("key", "cls", "n", "part"), name)


def distinct_groups(rows: DataFrame, by_key) -> DataFrame:
    """The same groups of classes with groups that have equal members (keys of one passage) once; only groups of ``SMALL`` or less are compared."""
    sized = rows.withColumn("size", F.count(F.lit(1)).over(by_key))
    small = sized.where(F.col("size") <= SMALL).groupBy("key").agg(F.sort_array(F.collect_list(F.struct("cls", "part"))).alias("members"))
    small = small.groupBy("members").agg(F.min("key").alias("key")).select("key", F.explode("members").alias("m")).select("key", "m.cls", "m.part")
    return small.unionByName(sized.where(F.col("size") > SMALL).select("key", "cls", "part"))


def _grouped(docs: DataFrame, percent: int) -> tuple[DataFrame, DataFrame, Workspace]:
    """(doc_id, cls, n, component) of all rows and (component, component_id) of those with words."""
    described, parts, work = join(docs, percent)
    rows = described.join(parts.withColumnRenamed("node", "cls"), "cls", "left").select("doc_id", "cls", "n", F.coalesce("component", "cls").alias("component"))
    return rows, rows.where("n > 0").groupBy("component").agg(F.min("doc_id").alias("component_id")), work


def join_report(docs: DataFrame, percent: int = 75) -> DataFrame:
    """doc_id, n_shingles, component_id: a row per row of ``docs``."""
    rows, lowest, _ = _grouped(docs.select("doc_id", "text"), percent)
    out = rows.where("n > 0").join(lowest, "component").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return out.unionByName(rows.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def one_of_each(docs: DataFrame, percent: int = 75) -> DataFrame:
    """One row of each component, the one with the smallest doc_id, columns unchanged; rows without words all stay.

    A component of null ids alone keeps one of its rows, and so does one whose smallest id
    several rows have: the first by text, then by a hash of all columns.
    """
    rows, lowest, work = _grouped(docs.select("doc_id", "text"), percent)
    rows = work.save(rows.join(lowest, "component", "left"), "grouped")
    wanted = (F.col("n") == 0) | F.col("doc_id").eqNullSafe(F.col("component_id"))
    ids = rows.groupBy("doc_id").agg(F.count(F.lit(1)).alias("k"), F.bool_or(wanted).alias("wanted")).where("wanted")
    ids = work.save(ids, "ids")
    work.keep("grouped", "ids")
    own = columns.prefix(docs, "one_")
    named = lambda df: df.withColumnsRenamed({c: f"{own}{c}" for c in df.columns})
    doc_id = F.col("doc_id")
    plain = docs.join(named(ids.where("k = 1 and doc_id is not null")), doc_id == F.col(f"{own}doc_id"), "left_semi")
    several = named(ids.where("k > 1 or doc_id is null").select("doc_id"))
    if several.isEmpty():
        return plain
    # ids that don't tell rows apart: these rows are told apart by their texts
    some = _with_class(docs.join(several, doc_id.eqNullSafe(F.col(f"{own}doc_id")), "left_semi"), f"{own}cls")
    classes = named(rows.where("n > 0").select("cls", "component", "component_id").distinct())
    some = some.join(classes.withColumnRenamed(f"{own}cls", f"{own}of"), F.col(f"{own}cls") == F.col(f"{own}of"), "left")
    empty = some.where(F.col(f"{own}component").isNull()).select(*columns.own(docs))
    whole, first = F.struct(*columns.own(docs)), F.struct("text", F.xxhash64(*[c.cast("string") for c in columns.own(docs)]))
    best = some.where(F.col(f"{own}component").isNotNull() & doc_id.eqNullSafe(F.col(f"{own}component_id"))).groupBy(f"{own}component").agg(F.min_by(whole, first).alias(f"{own}row"))
    return plain.unionByName(empty).unionByName(best.select(*[F.col(f"{own}row").getField(c).alias(c) for c in docs.columns]))


def _with_class(docs: DataFrame, name: str) -> DataFrame:
    """``docs`` with the class of each row's text; null for a text without words."""
    place = docs.columns.index("text")
    kind = T.StructType([*docs.schema.fields, T.StructField(name, T.LongType())])

    def read(batches):
        for batch in batches:
            found = [class_name(s) if len(s) else None for s in textkit.shingle_sets(batch.column(place))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.int64())], names=[*batch.schema.names, name])

    return docs.mapInArrow(textkit.frugal(read), kind)


from .decontaminate import _SHINGLES, _WORDS  # noqa: E402

#: DuckDB for ``join_report`` by shared shingles.
ORACLE = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_SHINGLES} AS s FROM (SELECT doc_id, {_WORDS} AS w FROM documents)),
u AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM d),
p AS (SELECT a.doc_id AS a, b.doc_id AS b FROM u a JOIN u b ON a.x = b.x AND a.doc_id <> b.doc_id AND 100 * least(a.n, b.n) >= 75 * greatest(a.n, b.n)
      GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))),
r AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT r.a, p.b FROM r JOIN p ON r.b = p.a)
SELECT d.doc_id, len(any_value(s))::BIGINT AS n_shingles, min(r.b)::BIGINT AS component_id FROM d JOIN r ON r.a = d.doc_id GROUP BY d.doc_id
"""
