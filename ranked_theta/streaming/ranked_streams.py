"""Ranked joins over streams.

* ``windowed_top_k``: the k best answers inside each closed window, once it is closed.
* ``ContinuousTopK``: the k best answers over all rows so far; a batch is joined with
  what came before, since every new answer has a new row.
* ``running_best``: keyed state, the lightest row of each key so far.
* ``interval_stream_join``: pairs of rows of two streams whose times lie within an interval.
* ``windowed_counts``: tumbling, sliding and session windows with a watermark.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import ranked
from ..operators.cursor import per_group
from ..plans.query import Query
from ..sources.staging import Staging


def windowed_top_k(batch: DataFrame, at: str, width: str, query_of: Callable[[DataFrame], Query], k: int) -> DataFrame:
    """k best answers per tumbling window of a (closed) batch: rank, weight, rid_1.., win.

    The window's start is an equality key of the query, so that one bottom-up pass serves
    all windows; each window is cut on its own.
    """
    rows = batch.withColumn("win", F.unix_micros(F.window(at, width).start.cast("timestamp")))
    return per_group(query_of(rows), "win", k).withColumnRenamed("group_key", "win")


def start_windowed(stream: DataFrame, at: str, width: str, late: str, query_of, k: int, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Runs ``windowed_top_k`` on rows gathered per window in append mode, so that only closed windows are joined.

    The state holds the rows of open windows. A window's rows are gathered in parts by a
    hash of the row, so that no state row holds a whole window.
    """
    columns = stream.columns
    part = F.pmod(F.xxhash64(*columns), F.lit(PARTS)).alias("part")
    closed = stream.withWatermark(at, late).groupBy(F.window(at, width), part).agg(F.collect_list(F.struct(*columns)).alias("rows"))

    def each(batch: DataFrame, number: int) -> None:
        if not batch.isEmpty():
            sink(windowed_top_k(batch.select(F.explode("rows").alias("r")).select("r.*"), at, width, query_of, k), number)

    return closed.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(each).trigger(availableNow=True).start()


#: Parts that the rows of a window are gathered in.
PARTS = 64


class ContinuousTopK:
    """State: all rows so far, a written table for each batch, and the current answers.

    ``query_of(frames)`` makes the query from one DataFrame per atom. For new rows D and
    old rows O, the answers with a new row are the disjoint union over the atoms i of
    (O for atoms before i, D for i, all rows after i). ``add`` can be given to
    ``foreachBatch``; a batch number that was seen is a repetition and changes nothing.
    """

    def __init__(self, spark: SparkSession, atoms: int, query_of: Callable[[list[DataFrame]], Query], k: int):
        self.spark, self.n, self.query_of, self.k = spark, atoms, query_of, k
        self.staging, self.turn, self.numbers = Staging(spark, "continuous"), 0, set()
        self.rows: DataFrame | None = None
        self.best: DataFrame | None = None

    def add(self, batch: DataFrame, number: int | None = None) -> DataFrame:
        if number is not None and number in self.numbers:
            return self.best
        self.numbers.add(number)
        self.turn += 1
        new = self.staging.save(batch, f"rows/batch={self.turn}")
        every = new if self.rows is None else self.rows.unionByName(new)
        found = self.best
        for i in range(self.n):
            if self.rows is None and i > 0:
                break
            frames = [self.rows] * i + [new] + [every] * (self.n - i - 1)
            one = ranked.top_k(self.query_of(frames), self.k).drop("rank")
            found = one if found is None else found.unionByName(one)
        ids = [f"rid_{i + 1}" for i in range(self.n)]
        self.best = self.staging.save(found.dropDuplicates(ids).orderBy("weight", *ids).limit(self.k), f"best{self.turn}")
        self.rows = every
        return self.best


def running_best(stream: DataFrame, key: str, rid: str, weight: str) -> DataFrame:
    """(key, rid, weight): the lightest row of each key so far, updated with each batch; of equal ones the smallest rid.

    Rows without weight or rid are left out.
    """

    def step(group, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best = tuple(state.get) if state.exists else None
        for pdf in batches:
            known = pdf[[weight, rid]].dropna()
            if len(known):
                w, r = known.sort_values([weight, rid]).iloc[0]
                best = (int(w), int(r)) if best is None else min(best, (int(w), int(r)))
        if best is not None:
            state.update(best)
            yield pd.DataFrame({key: [group[0]], rid: [best[1]], weight: [best[0]]})

    return stream.groupBy(key).applyInPandasWithState(step, f"{key} long, {rid} long, {weight} long", "w long, r long", "update", "NoTimeout")


def interval_stream_join(left: DataFrame, right: DataFrame, key_left: str, key_right: str, at_left: str, at_right: str, within: str, late: str) -> DataFrame:
    """Stream-stream join of rows with equal keys whose times lie within an interval, with watermarks on both sides."""
    a, b = left.withWatermark(at_left, late), right.withWatermark(at_right, late)
    return a.join(b, F.expr(f"{key_left} = {key_right} AND {at_right} > {at_left} AND {at_right} <= {at_left} + INTERVAL {within}"))


def windowed_counts(rows: DataFrame, at: str, late: str, kind: str, width: str, step: str | None = None, keys: list[str] = ()) -> DataFrame:
    """(keys, start, n) per window of a stream or a table; ``kind``: tumbling, sliding (every ``step``) or session (gaps of ``width``)."""
    if kind not in ("tumbling", "sliding", "session"):
        raise ValueError(f"unknown kind {kind}")
    if kind == "sliding" and step is None:
        raise ValueError("sliding windows need a step")
    window = F.session_window(at, width) if kind == "session" else F.window(at, width, step if kind == "sliding" else None)
    source = rows.withWatermark(at, late) if rows.isStreaming else rows
    return source.groupBy(*keys, window.alias("win")).agg(F.count(F.lit(1)).alias("n")).select(*keys, F.col("win.start").alias("start"), "n")


def run_to_end(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """All output of a stream over the input there is, as a table: appended rows, or with ``update`` the last row of each key.

    ``path``: a shared folder for the output and the checkpoint.
    """
    spark = stream.sparkSession

    def each(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch_number", F.lit(number)).write.mode("overwrite").parquet(f"{path}/out/part={number}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").foreachBatch(each).trigger(availableNow=True).start().awaitTermination()
    return spark.read.option("basePath", f"{path}/out").parquet(f"{path}/out").drop("part")
