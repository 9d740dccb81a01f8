"""Mixing sources to target weights by capped water-filling.

A source's target is its weight's part of ``share`` times the corpus size, but no more
than ``max_epochs`` times its own size; what the clamped sources leave goes to the rest
by weight. All is one closed form over the per-source table: sort sources by the level
at which they clamp, and the first one that the remaining budget cannot fill gives the
level for itself and all after it.

A document is taken floor(target / source size) times, and once more if it lies in the
seeded prefix that fills the fraction that is left: documents of a source in the order
of a hash of seed and id, as far as the middle of the document is within the budget.
The prefix is found from sums over 4,096 hash ranges, so that no window ever holds a
source, and is then one boundary per source: texts are never shuffled.

Nulls: a null text has size 0; a null source is a source of its own, ordered last;
a null id is hashed as the word "null". Repeated rows share their fate. A source of
size 0 has target 0 and nothing is taken from it. An empty table gives an empty result.
Other columns are carried along by ``mixed`` and ignored by ``plan_mix``.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import columns
from .workspace import Workspace

WORD = r"[^\x20\x09-\x0D]+"
_HEX = 3


def word_count(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def _source_key(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), source))


def _hash(doc_id: Column, seed: int) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("null"))).cast("binary"))


def water_fill(sizes: DataFrame, weights: Sequence[int], share: float, max_epochs: float) -> DataFrame:
    """(sk, source_size) -> with ``weight`` and ``target``; weights repeat over the sources in code point order, null last."""
    everyone = Window.partitionBy()
    by_level = Window.partitionBy().orderBy("level", "sk")
    order = Window.partitionBy().orderBy(F.when(F.col("sk") == "n", 1).otherwise(0), "sk")
    cycle = F.array(*[F.lit(int(w)).cast("long") for w in weights])
    table = sizes.withColumn("weight", F.element_at(cycle, ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int")))
    table = table.withColumn("cap", F.col("source_size") * F.lit(float(max_epochs))).withColumn("level", F.col("cap") / F.col("weight"))
    table = table.withColumns(
        {
            "left": F.sum("source_size").over(everyone) * F.lit(float(share)) - (F.sum("cap").over(by_level.rowsBetween(Window.unboundedPreceding, 0)) - F.col("cap")),
            "rest": F.sum("weight").over(everyone) - (F.sum("weight").over(by_level.rowsBetween(Window.unboundedPreceding, 0)) - F.col("weight")),
            "place": F.row_number().over(by_level),
        }
    )
    table = table.withColumn("open", F.col("left") * F.col("weight") <= F.col("cap") * F.col("rest"))
    first = F.min(F.when(F.col("open"), F.struct("place", "left", "rest"))).over(everyone)
    table = table.withColumn("first", first)
    target = F.when(F.col("first").isNull() | (F.col("place") < F.col("first.place")), F.col("cap")).otherwise(F.col("weight") * F.col("first.left") / F.col("first.rest"))
    return table.select("sk", "source_size", "weight", target.cast("double").alias("target"))


def plan_mix(docs: DataFrame, work: Workspace, *, weights: Sequence[int] = (3, 1, 2), share: float = 1.5, max_epochs: float = 2.0, seed: int = 7) -> DataFrame:
    """One row per source: sk, source_size, target, whole, and the boundary of the extra repetition."""
    base = docs.select(_source_key(F.col("source")).alias("sk"), _hash(F.col("doc_id"), seed).alias("key"), F.coalesce(F.col("doc_id"), F.lit(-(2**63))).alias("id"), F.col("text"))
    base = base.withColumn("bucket", F.substring("key", 1, _HEX))
    parts = work.save(base.groupBy("sk", "bucket").agg(F.sum(word_count(F.col("text"))).alias("part")), "parts")
    targets = work.save(water_fill(parts.groupBy("sk").agg(F.sum("part").alias("source_size")), weights, share, max_epochs), "targets")
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    targets = targets.withColumn("whole", whole).withColumn("fraction", F.col("target") - F.col("whole") * F.col("source_size"))
    running = Window.partitionBy("sk").orderBy("bucket")
    parts = parts.withColumn("before", F.sum("part").over(running.rowsBetween(Window.unboundedPreceding, 0)) - F.col("part"))
    edge = parts.join(targets.select("sk", "fraction"), "sk").where(F.col("before") + F.col("part") > F.col("fraction"))
    edge = work.save(edge.groupBy("sk").agg(F.min(F.struct("bucket", "before", "fraction")).alias("e")).select("sk", "e.*"), "edges")
    inside = base.join(edge, ["sk", "bucket"]).withColumn("size", word_count(F.col("text")))
    inside = inside.groupBy("sk", "bucket", "before", "fraction", "key", "id", "size").agg(F.count(F.lit(1)).alias("n"))
    local = Window.partitionBy("sk", "bucket").orderBy("key", "id", "size").rowsBetween(Window.unboundedPreceding, 0)
    own = F.col("n") * F.col("size")
    inside = inside.withColumn("ahead", F.col("before") + F.sum(own).over(local) - own)
    bounds = inside.where(2 * F.col("ahead") + own <= 2 * F.col("fraction")).groupBy("sk").agg(F.max(F.struct("key", "id", "size")).alias("bound"))
    return work.save(targets.join(edge.select("sk", "bucket"), "sk", "left").join(bounds, "sk", "left"), "plan")


def decide(docs: DataFrame, plan: DataFrame, seed: int = 7, named: str = "mix_") -> DataFrame:
    """Adds size, source_size, target and copies to every row of ``docs``, under names that begin with ``named``.

    The caller sees to it that no column of ``docs`` begins so (``columns.prefix``).
    """
    sk, key, size, row_id = (f"{named}{x}" for x in ("sk", "key", "size", "id"))
    rows = docs.withColumns({sk: _source_key(F.col("source")), key: _hash(F.col("doc_id"), seed), size: word_count(F.col("text")), row_id: F.coalesce(F.col("doc_id"), F.lit(-(2**63)))})
    p = {c: F.col(f"{named}p_{c}") for c in plan.columns}
    rows = rows.join(plan.select(*[F.col(c).alias(f"{named}p_{c}") for c in plan.columns]), F.col(sk) == p["sk"], "left")
    mine = F.struct(F.col(key).alias("key"), F.col(row_id).alias("id"), F.col(size).alias("size"))
    bucket = F.substring(key, 1, _HEX)
    extra = p["bucket"].isNotNull() & ((bucket < p["bucket"]) | ((bucket == p["bucket"]) & F.coalesce(mine <= p["bound"], F.lit(False))))
    copies = p["whole"] + F.when(extra, 1).otherwise(0)
    return rows.select(*columns.own(docs), size, p["source_size"].alias(f"{named}source_size"), p["target"].alias(f"{named}target"), copies.cast("long").alias(f"{named}copies"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as it is taken, columns unchanged whatever their names."""
    work = Workspace(docs.sparkSession, "mix")
    named = columns.prefix(docs, "mix_")
    rows = decide(docs, plan_mix(docs, work, **options), options.get("seed", 7), named)
    copies = F.col(f"{named}copies")
    rows = rows.where(copies > 0).withColumn(f"{named}copy", F.explode(F.sequence(F.lit(1).cast("long"), copies)))
    return rows.select(*columns.own(docs))


def mix_report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target and taken (words of the document in the mix)."""
    docs = docs.select("doc_id", "source", "text")
    work = Workspace(docs.sparkSession, "mix")
    rows = decide(docs, plan_mix(docs, work, **options), options.get("seed", 7))
    return rows.select("doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("mix_size") * F.col("mix_copies")).alias("taken"))


#: DuckDB for ``mix_report`` with the default parameters.
ORACLE = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
                  md5('7:' || coalesce(CAST(doc_id AS VARCHAR), 'null')) AS k FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, source_size * 2.0::DOUBLE AS cap FROM s),
l AS (SELECT *, row_number() OVER o AS place, sum(source_size) OVER () * 1.5::DOUBLE - (sum(cap) OVER (o ROWS UNBOUNDED PRECEDING) - cap) AS budget,
             sum(weight) OVER () - (sum(weight) OVER (o ROWS UNBOUNDED PRECEDING) - weight) AS rest
      FROM w WINDOW o AS (ORDER BY cap / weight, source ASC NULLS FIRST)),
f AS (SELECT * FROM l WHERE budget * weight <= cap * rest ORDER BY place LIMIT 1),
t AS (SELECT l.source, l.source_size, CASE WHEN l.place < f.place THEN l.cap ELSE l.weight * f.budget / f.rest::DOUBLE END AS target FROM l LEFT JOIN f ON true),
r AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
c AS (SELECT d.doc_id, d.size, r.source_size, r.target, r.whole, r.target - r.whole * r.source_size AS fraction,
             sum(d.size) OVER (PARTITION BY d.source ORDER BY d.k, d.doc_id, d.size RANGE UNBOUNDED PRECEDING) AS upto,
             sum(d.size) OVER (PARTITION BY d.source, d.k, d.doc_id, d.size) AS own
      FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source)
SELECT doc_id, size::BIGINT AS size, source_size, target::DOUBLE AS target,
       (size * (whole + CASE WHEN 2 * (upto - own) + own <= 2 * fraction THEN 1 ELSE 0 END))::BIGINT AS taken FROM c
"""
