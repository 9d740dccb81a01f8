"""Embedding near-duplicates: sign hashing in several tables, exact cosine, components.

Vectors are compared only where labels are equal. Equal vectors form a class, which is
hashed once. A table's code is the signs of random hyperplanes; codes have more bits
the more classes the largest label has, and there are as many tables as make a pair at
the threshold share a bucket with the recall asked for. In each bucket the cosines are
computed in double precision. A pair is counted in the first table that it shares, so
counts need no list of pairs, and a bucket gives one link per vector (to the first one
of its local component), so links stay linear in the vectors. A bucket above ``BLOCK``
classes is dealt into blocks and done by pairs of blocks, which bounds memory without
leaving out a pair.

Labels may be of any type with a text form; they are dealt by a hash and compared as they
are. Components may be of any size that a double holds.

Nulls: vectors that are null, empty, zero, or hold null or non-finite components, and
those without label, link with nothing, as do vectors of different lengths. A row
without vec_id links with nothing and has component null and kept false. Repeated rows
are vectors of their own, linked with each other. Empty table: empty result.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import groups
from .components import components
from .workspace import Workspace

#: Classes of a bucket that are compared at once.
BLOCK = 1024
#: Classes that a bucket should hold on average.
BUCKET = 32


def shape_of_tables(classes: int, threshold: float, recall: float) -> tuple[int, int]:
    """Bits of a code, and tables."""
    bits = min(30, max(8, math.ceil(math.log2(max(1, classes) / BUCKET))))
    same = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(1 - same)))


def _valid(rows: DataFrame) -> DataFrame:
    """vec_id, label (as text), cls (a class of equal vectors under equal labels), vec.

    Vectors are scaled by a power of two, so that the largest component is between a half
    and one: no square overflows or vanishes, and cosines stay as they are.
    """
    schema = pa.schema([("vec_id", pa.int64()), ("label", pa.string()), ("cls", pa.int64()), ("vec", pa.binary())])

    def pick(batches):
        for batch in batches:
            out = {name: [] for name in schema.names}
            column = batch.column(2)
            flat = column.flatten() if len(column) else pa.array([], pa.float64())
            off = np.concatenate([[0], np.cumsum(np.diff(column.offsets.to_numpy()) * column.is_valid().to_numpy(zero_copy_only=False))]) if len(column) else np.zeros(1, np.int64)
            values, ok = flat.to_numpy(zero_copy_only=False).astype(np.float64), flat.is_valid().to_numpy(zero_copy_only=False)
            ok = ok & np.isfinite(values)
            for i, (vec_id, label) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                a, b = int(off[i]), int(off[i + 1])
                if vec_id is None or label is None or a == b or not ok[a:b].all() or not values[a:b].any():
                    continue
                exponent = int(np.frexp(np.abs(values[a:b]).max())[1])
                half = exponent // 2  # in two steps, as the whole factor may be out of range
                vec = (np.ldexp(np.ldexp(values[a:b], -half), half - exponent) + 0.0).tobytes()  # + 0.0 makes one zero of two
                name = hashlib.blake2b(vec, digest_size=8, key=hashlib.blake2b(label.encode(), digest_size=32).digest()).digest()
                for key, value in zip(out, (vec_id, label, int.from_bytes(name, "big", signed=True), vec), strict=True):
                    out[key].append(value)
            yield pa.RecordBatch.from_pydict(out, schema=schema)

    label = F.col("label") + 0 if dict(rows.dtypes)["label"] in ("float", "double") else F.col("label")
    return rows.select(F.col("vec_id").cast("long"), label.cast("string"), "embedding").mapInArrow(pick, "vec_id long, label string, cls long, vec binary")


def _coded(classes: DataFrame, bits: int, tables: int, seed: int, with_vectors: bool) -> DataFrame:
    """A row for each class and table: hash of label and length in ``grp``, table and code in ``code``."""
    fields = [("grp", pa.int64()), ("code", pa.int64()), ("cls", pa.int64())] + [("n", pa.int64()), ("label", pa.string()), ("vec", pa.binary()), ("codes", pa.binary())] * with_vectors

    def code(batches):
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            rows = batch.to_pydict()
            for size in sorted({len(v) for v in rows["vec"]}):
                at = [i for i, v in enumerate(rows["vec"]) if len(v) == size]
                if size not in planes:
                    planes[size] = np.random.default_rng((seed, size)).normal(size=(size // 8, bits * tables))
                signs = np.frombuffer(b"".join(rows["vec"][i] for i in at)).reshape(len(at), -1) @ planes[size] >= 0
                codes = signs.reshape(len(at), tables, bits) @ (1 << np.arange(bits, dtype=np.int64))
                out = {
                    "grp": np.repeat(np.array([group_of(rows["label"][i], size) for i in at], np.int64), tables),
                    "code": (codes + (np.arange(tables, dtype=np.int64) << 32)).reshape(-1),
                    "cls": np.repeat([rows["cls"][i] for i in at], tables),
                }
                if with_vectors:
                    own = [c.astype("<i4").tobytes() for c in codes]
                    out |= {"n": np.repeat([rows["n"][i] for i in at], tables), "label": [rows["label"][i] for i in at for _ in range(tables)], "vec": [rows["vec"][i] for i in at for _ in range(tables)], "codes": [c for c in own for _ in range(tables)]}
                made = pa.RecordBatch.from_pydict(out, schema=pa.schema(fields))
                for a in range(0, made.num_rows, 4096):
                    yield made.slice(a, 4096)

    return classes.select("label", "cls", "n", "vec").mapInArrow(code, ", ".join(f"{n} { {pa.binary(): 'binary', pa.string(): 'string'}.get(t, 'long')}" for n, t in fields))


def group_of(label: str, size: int) -> int:
    return int.from_bytes(hashlib.blake2b(label.encode(), digest_size=8, salt=size.to_bytes(8, "big")).digest(), "big", signed=True)


def _roots(near: np.ndarray) -> np.ndarray:
    """The first row of each row's component, from a symmetric boolean matrix."""
    root = np.full(len(near), -1)
    for s in range(len(near)):
        if root[s] >= 0:
            continue
        root[s] = s
        front = np.array([s])
        while len(front):
            front = np.flatnonzero(near[front].any(0) & (root < 0))
            root[front] = s
    return root


def compare(cls: np.ndarray, weight: np.ndarray, vec: np.ndarray, codes: np.ndarray, table: int, side: np.ndarray | None, threshold: float, label: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Links that each class gets here (by weight, those of earlier tables left out), and the first row of its local component.

    ``side``: the block of each row if only rows of different blocks are compared;
    ``label``: the labels where a bucket has several of them.
    """
    size = np.linalg.norm(vec, axis=1)
    near = (vec @ vec.T) / (size[:, None] * size[None, :]) >= threshold
    np.fill_diagonal(near, False)
    near &= cls[:, None] != cls[None, :]
    if side is not None:
        near &= side[:, None] != side[None, :]
    if label is not None:
        near &= label[:, None] == label[None, :]
    count = near.copy()
    for t in range(table):
        count &= codes[:, t, None] != codes[None, :, t]
    return count @ weight, _roots(near)


def links(classes: DataFrame, work: Workspace, threshold: float, recall: float, seed: int) -> DataFrame:
    """(cls, n_add, root): a row for each bucket in which a class has a link."""
    spark = classes.sparkSession
    most = classes.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    bits, tables = shape_of_tables(most, threshold, recall)
    large = _coded(classes, bits, tables, seed, False).groupBy("grp", "code").count().where(F.col("count") > BLOCK)
    large = work.save(large.select("grp", "code", F.ceil(F.col("count") / BLOCK).cast("long").alias("blocks")), "large")
    rows = _coded(classes, bits, tables, seed, True).join(large, ["grp", "code"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    own = F.pmod(F.xxhash64("cls"), F.col("blocks"))
    # a row of block i goes to the pairs (i, j) and (j, i) of blocks, the smaller first
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))
    rows = rows.withColumn("own", own).withColumn("other", other)
    rows = rows.withColumn("pair", F.least("own", "other") * F.col("blocks") + F.greatest("own", "other"))
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = rows.repartition(n, "grp", "code", "pair").sortWithinPartitions("grp", "code", "pair")
    schema = pa.schema([("cls", pa.int64()), ("n_add", pa.int64()), ("root", pa.int64())])

    def bucket(batches):
        for table, bounds in groups.runs(batches, 3):
            code, cls, n = (table.column(k).to_numpy() for k in ("code", "cls", "n"))
            own, same = table.column("own").to_numpy(), table.column("same").to_numpy()
            vec, codes, label = table.column("vec"), table.column("codes"), table.column("label")
            out: list[list] = [[], [], []]
            for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                if b - a < 2:
                    continue
                # labels and lengths of one hash are told apart here
                names = label.slice(int(a), int(b - a)).dictionary_encode().combine_chunks()
                several = names.indices.to_numpy() if len(names.dictionary) > 1 else None
                raw = [vec[i].as_py() for i in range(a, b)]
                if len({len(x) for x in raw}) > 1:
                    raise ValueError("two lengths of vectors have one hash; use another one")
                v = np.frombuffer(b"".join(raw)).reshape(b - a, -1)
                c = np.frombuffer(b"".join(codes[i].as_py() for i in range(a, b)), "<i4").reshape(b - a, -1)
                side = None if same[a] else own[a:b]
                add, root = compare(cls[a:b], n[a:b], v, c, int(code[a] >> 32), side, threshold, several)
                size = np.bincount(root, minlength=b - a)[root]
                for i in np.flatnonzero((add > 0) | (size > 1)):
                    out[0].append(int(cls[a + i]))
                    out[1].append(int(add[i]))
                    out[2].append(int(cls[a + root[i]]))
            yield pa.RecordBatch.from_pydict(dict(zip(schema.names, out, strict=True)), schema=schema)

    return rows.select("grp", "code", "pair", "cls", "n", "label", "vec", "codes", "own", (F.col("own") == F.col("other")).alias("same")).mapInArrow(bucket, "cls long, n_add long, root long")


def near_duplicates(rows: DataFrame, threshold: float = 0.98, recall: float = 0.99999, seed: int = 3) -> DataFrame:
    """vec_id, n_links, component_id, kept: a row per row of ``rows``."""
    work = Workspace(rows.sparkSession, "embeddings")
    valid = _valid(rows)
    members = work.save(valid.select("vec_id", "cls"), "members")
    classes = work.save(valid.groupBy("label", "cls").agg(F.count(F.lit(1)).alias("n"), F.min("vec_id").alias("first"), F.min("vec").alias("vec")), "classes")
    found = work.save(links(classes, work, threshold, recall, seed), "links")
    counts = found.groupBy("cls").agg(F.sum("n_add").alias("n_add"))
    parts = components(found.select(F.col("cls").alias("a"), F.col("root").alias("b")), work).withColumnRenamed("node", "cls")
    joined = classes.select("cls", "n", "first").join(counts, "cls", "left").join(parts, "cls", "left").withColumn("component", F.coalesce("component", "cls"))
    lowest = joined.groupBy("component").agg(F.min("first").alias("component_id"))
    known = joined.join(lowest, "component").select("cls", (F.coalesce("n_add", F.lit(0)) + F.col("n") - 1).alias("n_links"), "component_id")
    known = work.save(known, "known")
    linked = members.join(known, "cls").select("vec_id", "n_links", "component_id")
    # rows that link with nothing have no class; repeated vec_ids may be in several
    alone = rows.select(F.col("vec_id").cast("long")).join(members.select("vec_id").distinct(), "vec_id", "left_anti")
    out = linked.unionByName(alone.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id")))
    return out.select("vec_id", "n_links", "component_id", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)).alias("kept"))


#: DuckDB for ``near_duplicates`` by all pairs.
ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
l AS (SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id
      AND list_cosine_similarity(a.e, b.e) >= 0.98::DOUBLE),
r AS (SELECT vec_id AS x, vec_id AS y FROM v UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x)
SELECT vec_id, (SELECT count(*) FROM l WHERE l.x = vec_id)::BIGINT AS n_links, min(y)::BIGINT AS component_id, min(y) = vec_id AS kept
FROM v JOIN r ON r.x = vec_id GROUP BY vec_id
"""
