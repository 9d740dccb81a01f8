"""Token counts of a corpus: an exact histogram of encoded lengths and its suffix sums.

Documents are encoded where they are read and aggregated by length there, so that only
(length, documents) pairs are shuffled; texts never are. All else is sums over that
histogram: with the documents and tokens at or above a length, the corpus cut to a
context limit has ``tokens below the limit + limit * documents at or above it`` tokens.
The sums run within ranges of 1,024 lengths on top of the totals of the ranges above, so
that no window holds more than one range or the table of ranges.

Between two lengths that occur, every sum is linear in the limit, so ``at_every_limit``
fills in each limit from its next length upwards, without a window.

Nulls: a null text is empty, so that it has the end id only, as in ``tokenids``. Ids are
not looked at, and repeated rows count each. Empty table: empty result.
"""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .tokenids import encoder
from .workspace import Workspace

#: Lengths of a range, as a power of two.
RANGE_BITS = 10


def histogram(docs: DataFrame, path: str, end_id: int | None = 1, chunked: bool = True) -> DataFrame:
    """(n_tokens, docs): how many documents have each encoded length."""
    schema = pa.schema([("n_tokens", pa.int64()), ("docs", pa.int64())])

    def count(batches):
        found = Counter()
        for batch in batches:
            found.update(map(len, encoder(path).encode(batch.column(0), end_id, chunked)))
        yield pa.RecordBatch.from_pydict({"n_tokens": list(found), "docs": list(found.values())}, schema=schema)

    return docs.select("text").mapInArrow(count, "n_tokens long, docs long").groupBy("n_tokens").agg(F.sum("docs").alias("docs"))


def suffix_sums(lengths: DataFrame) -> DataFrame:
    """Adds at_least (documents as long or longer), at_least_tokens (their tokens), all_docs and all_tokens."""
    mine = lengths.withColumns({"bin": F.shiftright("n_tokens", RANGE_BITS), "tokens": F.col("n_tokens") * F.col("docs")})
    everyone, above = Window.partitionBy(), Window.partitionBy().orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)
    bins = mine.groupBy("bin").agg(F.sum("docs").alias("bin_docs"), F.sum("tokens").alias("bin_tokens"))
    bins = bins.select(
        "bin",
        (F.sum("bin_docs").over(above) - F.col("bin_docs")).alias("docs_above"),
        (F.sum("bin_tokens").over(above) - F.col("bin_tokens")).alias("tokens_above"),
        F.sum("bin_docs").over(everyone).alias("all_docs"),
        F.sum("bin_tokens").over(everyone).alias("all_tokens"),
    )
    local = Window.partitionBy("bin").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    mine = mine.withColumns({"here_docs": F.sum("docs").over(local), "here_tokens": F.sum("tokens").over(local)})
    at_least, tokens = F.col("here_docs") + F.col("docs_above"), F.col("here_tokens") + F.col("tokens_above")
    return mine.join(bins, "bin").select("n_tokens", "docs", at_least.alias("at_least"), tokens.alias("at_least_tokens"), "all_docs", "all_tokens")


def at_every_limit(lengths: DataFrame) -> DataFrame:
    """A row per context limit from 0 to the greatest length.

    docs: documents of just that length; docs_within: of at most that length; percentile:
    whole hundredths of all documents that these are, so that the q-th percentile of
    lengths is the least limit whose percentile is q or more; truncated_tokens: tokens if
    every document is cut at the limit; lost_tokens: what the cuts take;
    at_least_tokens: tokens of the documents as long or longer, uncut.
    """
    sums = suffix_sums(lengths)
    before = _length_before(lengths)
    limit: Column = F.col("limit")
    here = limit == F.col("n_tokens")
    rows = sums.join(before, "n_tokens").withColumn("limit", F.explode(F.sequence(F.col("before") + 1, F.col("n_tokens"))))
    within = F.col("all_docs") - F.col("at_least") + F.when(here, F.col("docs")).otherwise(F.lit(0))
    cut = F.col("all_tokens") - F.col("at_least_tokens") + limit * F.col("at_least")
    return rows.select(
        limit,
        F.when(here, F.col("docs")).otherwise(F.lit(0)).cast("long").alias("docs"),
        within.cast("long").alias("docs_within"),
        F.expr("100 * (all_docs - at_least + CASE WHEN limit = n_tokens THEN docs ELSE 0 END) DIV all_docs").alias("percentile"),
        cut.alias("truncated_tokens"),
        (F.col("all_tokens") - cut).alias("lost_tokens"),
        "at_least_tokens",
        "all_docs",
        "all_tokens",
    )


def _length_before(lengths: DataFrame) -> DataFrame:
    """(n_tokens, before): the next smaller length that occurs, -1 for the least."""
    mine = lengths.select("n_tokens", F.shiftright("n_tokens", RANGE_BITS).alias("bin"))
    bins = mine.groupBy("bin").agg(F.max("n_tokens").alias("greatest"))
    bins = bins.select("bin", F.lag("greatest").over(Window.partitionBy().orderBy("bin")).alias("below"))
    inside = F.lag("n_tokens").over(Window.partitionBy("bin").orderBy("n_tokens"))
    return mine.withColumn("inside", inside).join(bins, "bin").select("n_tokens", F.coalesce("inside", "below", F.lit(-1).cast("long")).alias("before"))


def count_report(docs: DataFrame, path: str, end_id: int | None = 1) -> DataFrame:
    """The histogram of all texts, written once, and its sums at every context limit."""
    work = Workspace(docs.sparkSession, "lengths")
    return at_every_limit(work.save(histogram(docs, path, end_id), "histogram"))
