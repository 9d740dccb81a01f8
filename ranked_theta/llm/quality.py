"""Quality classifier: random-indexing word vectors, pooled, and a two-layer network.

Each word has two hashed identities: its own (A-Z as a-z) and its shape (letters and
digits reduced to their class, other characters kept). Every identity has a sparse
random index vector; its context vector is its own index vector and those of the shapes
next to it, summed over all documents, damped and normalised. A document's vector is the
mean of the context vectors of its words in both identities. A numpy network with one
hidden layer is fitted to labelled rows, and its logit is divided by a temperature that
minimises the log loss on rows kept back for that.

Labels come only from rows that are not held out (crc32 of the id's text mod 5 is not 0);
the fit uses at most ``train_rows`` of them, those with the smallest hash of id. Context
vectors are counted over all documents, labels play no part in them.

Nulls: a null text is empty and scores what the zero vector scores; a null id counts as
an empty text in the hold-out rule. Labels that are null or neither 0 nor 1 are ignored;
of contradicting labels of an id the larger counts. With fewer than two classes among
the labels every score is the share of label 1 (0.5 without labels). Empty table: empty
result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import columns, partials, textkit
from .workspace import Workspace

#: Identities of each kind (a power of two) and dimensions of their vectors.
IDENTITIES, DIMENSIONS, NONZERO = 1024, 64, 6
#: Labelled rows that the network is fitted to, at most.
TRAIN_ROWS = 20_000
THRESHOLD = 0.3
HIDDEN, EPOCHS, BATCH, RATE, DECAY = 32, 40, 128, 3e-3, 1e-4

_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[65:91] = 65
_SHAPE[97:123] = 97
_SHAPE[128:] = 97
_SHAPE[48:58] = 48


def index_vectors(seed: int) -> np.ndarray:
    """Sparse ternary vectors, one for each shape."""
    rng = np.random.default_rng(seed)
    out = np.zeros((IDENTITIES, DIMENSIONS), np.int64)
    for row in out:
        row[rng.choice(DIMENSIONS, NONZERO, replace=False)] = rng.choice([-1, 1], NONZERO)
    return out


def identities(part: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Own and shape identity of every word, and word bounds of the texts."""
    (own, shape), bounds = textkit.words_by(*textkit.utf8(part), textkit._FOLD, _SHAPE)
    top = np.uint64(64 - IDENTITIES.bit_length() + 1)
    return (own >> top).astype(np.int64), (shape >> top).astype(np.int64), bounds


def context_counts(docs: DataFrame) -> np.ndarray:
    """How often each identity (own, then shape) stands next to each shape, over all documents."""
    k = IDENTITIES

    def count(batches):
        from pyspark import TaskContext

        total = np.zeros((2, k * k), np.int64)
        for batch in batches:
            for part in textkit.slices(batch.column(0)):
                own, shape, bounds = identities(part)
                if len(own) < 2:
                    continue
                inside = np.ones(len(own) - 1, bool)
                edges = bounds[1:-1]
                inside[edges[(edges > 0) & (edges < len(own))] - 1] = False
                for i, left in enumerate((own, shape)):
                    total[i] += np.bincount(left[:-1][inside] * k + shape[1:][inside], minlength=k * k)
                    total[i] += np.bincount(left[1:][inside] * k + shape[:-1][inside], minlength=k * k)
        # sums of index vectors; whole numbers, so that the order of adding is no matter
        sums = total.reshape(2 * k, k) @ index_vectors(11)
        yield pa.RecordBatch.from_pydict(partials.rows(sums, TaskContext.get().partitionId()), schema=pa.schema([("piece", pa.int32()), ("salt", pa.int32()), ("part", pa.binary())]))

    return partials.collect(docs.select("text").mapInArrow(textkit.frugal(count), partials.SCHEMA), 2 * k * DIMENSIONS).reshape(2 * k, DIMENSIONS)


def context_vectors(sums: np.ndarray) -> np.ndarray:
    """Damped and normalised; an identity without context keeps a share of its index vector."""
    damped = np.sign(sums) * np.log1p(np.abs(sums))
    own = np.concatenate([index_vectors(13), index_vectors(11)])
    size = np.linalg.norm(damped, axis=1, keepdims=True)
    return np.where(size > 0, damped / np.maximum(size, 1e-12), 0.0) + own / np.sqrt(NONZERO)


def pooled(part: pa.Array, vectors: np.ndarray) -> np.ndarray:
    """A row for each text: mean context vector by own identity and by shape."""
    own, shape, bounds = identities(part)
    k, n = IDENTITIES, np.diff(bounds)
    out = np.zeros((len(part), 2 * DIMENSIONS))
    for a in range(0, len(part), 256):
        b = min(a + 256, len(part))
        row = np.repeat(np.arange(b - a), n[a:b]) * k
        for i, ids in enumerate((own, shape)):
            counts = np.bincount(row + ids[bounds[a] : bounds[b]], minlength=(b - a) * k).reshape(b - a, k)
            out[a:b, i * DIMENSIONS : (i + 1) * DIMENSIONS] = counts @ vectors[i * k : (i + 1) * k] / np.maximum(n[a:b, None], 1)
    return out


def _log_loss(logit: np.ndarray, y: np.ndarray) -> float:
    return float(np.mean(np.logaddexp(0, -logit) * y + np.logaddexp(0, logit) * (1 - y)))


class Network:
    """Standardised input, tanh layer, logit, temperature; fitted by Adam on the log loss."""

    def __init__(self, x: np.ndarray, y: np.ndarray, seed: int = 5):
        self.flat = None
        if len(np.unique(y)) < 2:
            self.flat = float(np.mean(y)) if len(y) else 0.5
            return
        rng = np.random.default_rng(seed)
        order = rng.permutation(len(x))
        back, fit = order[: len(x) // 5], order[len(x) // 5 :]
        self.mean, self.scale = x[fit].mean(0), x[fit].std(0) + 1e-6
        z = (x - self.mean) / self.scale
        w = [rng.normal(0, 1 / np.sqrt(z.shape[1]), (z.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN), np.zeros(1)]
        m, v, step = [np.zeros_like(p) for p in w], [np.zeros_like(p) for p in w], 0
        for _ in range(EPOCHS):
            for at in np.array_split(rng.permutation(fit), max(1, len(fit) // BATCH)):
                a, t = z[at], y[at]
                h = np.tanh(a @ w[0] + w[1])
                d = (1 / (1 + np.exp(-np.clip(h @ w[2] + w[3], -30, 30))) - t) / len(at)
                e = np.outer(d, w[2]) * (1 - h * h)
                step += 1
                for i, g in enumerate((a.T @ e + DECAY * w[0], e.sum(0), h.T @ d + DECAY * w[2], np.array([d.sum()]))):
                    m[i] = 0.9 * m[i] + 0.1 * g
                    v[i] = 0.999 * v[i] + 0.001 * g * g
                    w[i] = w[i] - RATE * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
        self.w, self.temperature = w, 1.0
        if len(back) and len(np.unique(y[back])) == 2:
            logit = self.logit(x[back])
            self.temperature = min(np.geomspace(0.25, 8, 101), key=lambda t: _log_loss(logit / t, y[back]))

    def logit(self, x: np.ndarray) -> np.ndarray:
        h = np.tanh((x - self.mean) / self.scale @ self.w[0] + self.w[1])
        return h @ self.w[2] + self.w[3]

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.flat is not None:
            return np.full(len(x), self.flat)
        return np.round(1 / (1 + np.exp(-np.clip(self.logit(x) / self.temperature, -30, 30))), 6)


def held_out(doc_id):
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS) -> tuple[np.ndarray, Network]:
    """Context vectors over all documents and the network of at most ``train_rows`` labels."""
    work = Workspace(docs.sparkSession, "quality")
    vectors = context_vectors(context_counts(docs))
    marked = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("quality").cast("long").alias("quality"))
    known = docs.select("doc_id").where(F.col("doc_id").isNotNull()).distinct()
    chosen = work.save(marked.join(known, "doc_id", "left_semi").orderBy(F.md5(F.col("doc_id").cast("string").cast("binary")), "doc_id").limit(train_rows), "labels")

    def features(batches):
        for batch in batches:
            at = 0
            for part in textkit.slices(batch.column(2)):
                n = len(part)
                yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0).slice(at, n), "quality": batch.column(1).slice(at, n), "x": [r.tobytes() for r in pooled(part, vectors)]}, schema=pa.schema([("doc_id", pa.int64()), ("quality", pa.int64()), ("x", pa.binary())]))
                at += n

    # the right side has train_rows rows of two numbers at most
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("doc_id", "quality", "text").mapInArrow(textkit.frugal(features), "doc_id long, quality long, x binary").groupBy("doc_id", "quality").agg(F.min("x").alias("x")).orderBy("doc_id").collect()
    x = np.array([np.frombuffer(r["x"]) for r in rows]).reshape(len(rows), 2 * DIMENSIONS)
    return vectors, Network(x, np.array([r["quality"] for r in rows], float))


def score(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` with quality_score and quality_predicted; columns of these names are replaced."""
    return _scored(docs, labels, train_rows, threshold, "quality_")


def _scored(docs: DataFrame, labels: DataFrame, train_rows: int, threshold: float, named: str) -> DataFrame:
    vectors, network = fit(docs, labels, train_rows)
    model = docs.sparkSession.sparkContext.broadcast((vectors, network))

    @F.pandas_udf("double")
    def rated(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        vec, net = model.value
        for batch in texts:
            column = pa.Array.from_pandas(batch, type=pa.string())
            yield pd.Series(np.concatenate([net.score(pooled(p, vec)) for p in textkit.slices(column)] or [np.zeros(0)]))

    out = docs.withColumn(f"{named}score", rated(F.col("text")))
    return out.withColumn(f"{named}predicted", F.when(F.col(f"{named}score") >= threshold, 1).otherwise(0).cast("int"))


def score_report(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    rows = score(docs.select("doc_id", "text"), labels.select("doc_id", "quality"), train_rows)
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("quality_score").alias("score"), F.col("quality_predicted").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that the classifier accepts, columns unchanged whatever their names."""
    named = columns.prefix(docs, "quality_")
    return _scored(docs, labels, train_rows, threshold, named).where(F.col(f"{named}predicted") == 1).select(*columns.own(docs))
