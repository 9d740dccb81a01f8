"""Folding a theta-join edge: for each source row the minimum or sum over its joining targets, without pairs.

A term's equalities are partition keys. All other comparisons but the last become node
choices (one row per level, see ``connectors.levels``); the last one needs no edges at
all: sources and targets of a node are sorted together and a running aggregate in
reading order gives each source what it may see. Frames only ever grow. That comparison
goes last which leaves the fewest rows, since each of the others costs rows by its bits.

Where rows multiply, only numbers do: sources are their ids and keys, and the values of
targets are replaced by their places in one sorted, written table, so that windows and
aggregates move and compare whole numbers. The rest of the columns is joined afterwards.

A partition that is too large for one task is cut into key ranges: running aggregates
stay inside a range, and one row per partition and range carries what lies beyond.

Sums over a disjunction are taken over terms that exclude each other, or by inclusion
and exclusion; minima need neither, since seeing a target twice does not change them.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from itertools import combinations
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.predicates import NEGATE, Compare, Opaque
from ..sources.staging import Staging
from . import connectors, ranks
from .joins import merged

#: Key ranges of a partition that is too large for one task.
RANGES = 64
#: Rows that a partition may have to be ordered in one task; affects the cost, not the result.
SPLIT = 1 << 17
#: Bits up to which the places inside a cell of a band serve as codes as they are.
CELL_BITS = 20


def _agg(fn: str, c: Column) -> Column:
    return F.min(c) if fn == "min" else F.sum(c)


def _merge(fn: str, a: Column, b: Column) -> Column:
    if fn == "min":
        return F.when(a.isNull() | (b < a), b).otherwise(a)
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(a + b)


def largest_group(df: DataFrame, columns: list[str]) -> int:
    """Rows of the largest group."""
    counted = df.groupBy(*columns).agg(F.count(F.lit(1)).alias("n"))
    return counted.agg(F.max("n")).first()[0] or 0


def _bounds(t: DataFrame, key: str, ranges: int) -> list:
    found = t.agg(F.percentile_approx(key, [i / ranges for i in range(1, ranges)], 1000)).first()[0]
    return sorted(set(found or []))


def _range_of(key: Column, kind: str, bounds: list) -> Column:
    """How many bounds lie below the key, as a balanced tree of comparisons."""

    def between(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        middle = (low + high) // 2
        return F.when(key <= F.lit(bounds[middle]).cast(kind), between(low, middle)).otherwise(between(middle + 1, high))

    return between(0, len(bounds))


def _running(rows: DataFrame, parts: list[str], op: str, fn: str, ranges: int) -> DataFrame:
    """``rows``: parts, _k (an ordered key), _src (1 for sources), _val (null for sources). Adds _seen for one strict or weak inequality."""
    up = op in ("<", "<=")  # targets above the source: read from the top
    strict = op in ("<", ">")
    tie = F.col("_src").desc() if strict else F.col("_src").asc()
    order = [F.col("_k").desc() if up else F.col("_k").asc(), tie]
    bounds = _bounds(rows.where("_src = 0"), "_k", ranges) if ranges > 1 else []
    if not bounds:
        w = Window.partitionBy(*parts).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
        return rows.withColumn("_seen", _agg(fn, F.col("_val")).over(w))
    rows = rows.withColumn("_b", _range_of(F.col("_k"), dict(rows.dtypes)["_k"], bounds))
    w = Window.partitionBy(*parts, "_b").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("_near", _agg(fn, F.col("_val")).over(w))
    # one row per partition and range that has rows at all
    beyond = rows.groupBy(*parts, "_b").agg(_agg(fn, F.col("_val")).alias("_own"))
    far = Window.partitionBy(*parts).orderBy(F.col("_b").desc() if up else F.col("_b").asc()).rowsBetween(Window.unboundedPreceding, -1)
    beyond = beyond.withColumn("_far", _agg(fn, F.col("_own")).over(far)).select(*parts, "_b", "_far")
    beyond = merged(beyond) if parts else F.broadcast(beyond)  # RANGES rows without parts
    rows = rows.join(beyond, [*parts, "_b"], "left")
    return rows.withColumn("_seen", _merge(fn, F.col("_near"), F.col("_far"))).drop("_b", "_near", "_far")


def _union(s: DataFrame, t: DataFrame, parts_s, parts_t, key_s, key_t, carried: list[str]) -> tuple[DataFrame, list[str]]:
    """Sources and targets as one table with the parts as _q0, _q1, and so on."""
    names = [f"_q{k}" for k in range(len(parts_s))]
    left = s.select(*[c.alias(n) for c, n in zip(parts_s, names, strict=True)], key_s.alias("_k"), F.lit(1).alias("_src"), F.struct("rid", *carried).alias("_row"))
    right = t.select(*[c.alias(n) for c, n in zip(parts_t, names, strict=True)], key_t.alias("_k"), F.lit(0).alias("_src"), F.col("val").alias("_val"))
    return left.unionByName(right, allowMissingColumns=True), names


class Values:
    """What folds need to know of the values that comparisons are made on; found for each fold anew.

    ``ranked.Passes`` has one that asks each relation once for a whole query.
    """

    def __init__(self, staging: Staging):
        self.staging = staging

    def both(self, s: DataFrame, t: DataFrame, a: str, b: str) -> DataFrame:
        return s.select(F.col(a).alias("v")).unionByName(t.select(F.col(b).alias("v")))

    def extent(self, pred: tuple, s: DataFrame, t: DataFrame) -> ranks.Extent:
        return ranks.extent(self.both(s, t, pred[1], pred[2]))

    def coding(self, pred: tuple, s: DataFrame, t: DataFrame, tag: str) -> ranks.Coding:
        both = self.both(s, t, pred[1], pred[2])
        return ranks.coding(both, ranks.extent(both), self.staging, tag)


def _ordered(s: DataFrame, t: DataFrame, rest: list[tuple], known: Values) -> list[tuple]:
    """The comparisons with that one last which leaves the fewest rows to order.

    A row becomes as many as the others have levels for it; the last one costs three rows
    if it is a band (cells) and two readings if it is a non-equality.
    """
    if len(rest) < 2:
        return rest
    copies = []
    for x in rest:
        p = x[0]
        bits = (p.eps - 1).bit_length() if p.op == "band" else 0
        if p.op != "band" or bits > CELL_BITS:
            bits = max(1, known.extent(x, s, t).distinct).bit_length()
        copies.append({"band": 1 + bits, "!=": bits}.get(p.op, bits / 2 + (p.op in ("<=", ">="))))
    last = min(range(len(rest)), key=lambda k: prod(c for j, c in enumerate(copies) if j != k) * {"band": 3, "!=": 2}.get(rest[k][0].op, 1))
    return [x for k, x in enumerate(rest) if k != last] + [rest[last]]


def _band_choices(s: DataFrame, t: DataFrame, pred: tuple, staging: Staging, tag: str, name: str) -> tuple[DataFrame, DataFrame, list[Column]]:
    """Node choices of a band: the cell and its kind, and levels inside the two neighbouring cells."""
    p, a, b = pred
    s, t = connectors.cells(s, a, p.eps, True, "_c"), connectors.cells(t, b, p.eps, False, "_c")
    kind, h = F.col("_c.kind"), F.col("_h")
    bits = max(1, (p.eps - 1).bit_length())
    if bits <= CELL_BITS:
        # what a neighbouring cell leaves to compare lies inside it
        inside = (F.col("_c.v") - F.col("_c.cell")).cast("long")
        s, t = s.withColumn("_v", inside), t.withColumn("_v", inside)
    else:
        s, t = s.withColumn("_v", F.col("_c.v")), t.withColumn("_v", F.col("_c.v"))
        s, t, bits = ranks.codes(s, t, "_v", "_v", staging, tag)

    def chosen(df: DataFrame, source: bool) -> DataFrame:
        # one level in the own cell; the target is below the source in the next one and above it in the one before
        rows = df.withColumn("_h", F.explode(F.when(kind == 0, F.array(F.lit(-1))).otherwise(F.sequence(F.lit(0), F.lit(bits - 1)))))
        bit = connectors.shift(F.col("_v"), F.greatest(h, F.lit(0))).bitwiseAND(F.lit(1))
        rows = rows.where((kind == 0) | (bit == F.when(kind == 1, F.lit(int(source))).otherwise(F.lit(int(not source)))))
        place = F.when(kind == 0, F.lit(0)).otherwise(connectors.shift(F.col("_v"), h + 1)).cast("long")
        return rows.withColumns({f"{name}k": kind, f"{name}c": F.col("_c.cell"), f"{name}h": h, f"{name}p": place}).drop("_c", "_v", "_h")

    return chosen(s, True), chosen(t, False), [F.col(f"{name}{x}") for x in "kchp"]


def _term_fold(s: DataFrame, t: DataFrame, term: list[tuple], fn: str, staging: Staging, tag: str, ranges: int, carried: list[str], known: Values) -> DataFrame:
    """(rid, carried, _seen) for one conjunction; a source can have several rows if the term has levels or cells."""
    t = t.select(*dict.fromkeys([b for _, _, b in term]), "val")
    for _, a, b in term:
        s, t = s.where(F.col(a).isNotNull()), t.where(F.col(b).isNotNull())
    equal, rest = [(a, b) for p, a, b in term if p.op == "="], [(p, a, b) for p, a, b in term if p.op != "="]
    if not rest:
        sums = t.groupBy(*[F.col(b).alias(f"_e{k}") for k, (_, b) in enumerate(equal)]).agg(_agg(fn, F.col("val")).alias("_seen"))
        if not equal:
            return s.crossJoin(F.broadcast(sums)).select("rid", *carried, "_seen")  # one row
        on = None
        for k, (a, _) in enumerate(equal):
            c = F.col(a) == F.col(f"_e{k}")
            on = c if on is None else on & c
        return s.join(sums, on).select("rid", *carried, "_seen")
    parts_s, parts_t = [F.col(a) for a, _ in equal], [F.col(b) for _, b in equal]
    rest = _ordered(s, t, rest, known)
    for k, (p, a, b) in enumerate(rest[:-1]):
        name = f"_p{k}"
        if p.op == "band":
            s, t, choice = _band_choices(s, t, (p, a, b), staging, f"{tag}-{k}", name)
            parts_s, parts_t = [*parts_s, *choice], [*parts_t, *choice]
            continue
        coding = known.coding((p, a, b), s, t, f"{tag}-{k}")
        s, t = coding.apply(s.withColumn("_c", F.col(a)), "_c"), coding.apply(t.withColumn("_c", F.col(b)), "_c")
        s, t = connectors.levels(s, "_c", p.op, coding.bits, True, name).drop("_c"), connectors.levels(t, "_c", p.op, coding.bits, False, name).drop("_c")
        parts_s, parts_t = [*parts_s, F.col(f"{name}.h"), F.col(f"{name}.p")], [*parts_t, F.col(f"{name}.h"), F.col(f"{name}.p")]
    p, a, b = rest[-1]
    if p.op == "band":
        # in the own cell all targets come before all sources; in the next one the lesser values, in the one before the greater
        s, t = connectors.cells(s, a, p.eps, True, "_c"), connectors.cells(t, b, p.eps, False, "_c")
        kind, value = F.col("_c.kind"), F.col("_c.v")
        place = lambda own: F.when(kind == 0, F.lit(own)).when(kind == 1, value).otherwise(-value).cast("long")
        rows, names = _union(s, t, [*parts_s, kind, F.col("_c.cell")], [*parts_t, kind, F.col("_c.cell")], place(1), place(0), carried)
        return _running(rows, names, ">", fn, ranges).where("_src = 1 and _seen is not null").select("_row.*", "_seen")
    if ranges > 1 and not _numeric(s, a):  # ranges are cut from numbers
        s, t = s.withColumn("_z", F.col(a)), t.withColumn("_z", F.col(b))
        s, t, _ = ranks.codes(s, t, "_z", "_z", staging, f"{tag}-last")
        a = b = "_z"
    rows, names = _union(s, t, parts_s, parts_t, F.col(a), F.col(b), carried)
    if p.op == "!=":
        below = _running(rows, names, ">", fn, ranges).withColumnRenamed("_seen", "_lower")
        rows = _running(below, names, "<", fn, ranges).withColumn("_seen", _merge(fn, F.col("_lower"), F.col("_seen")))
    else:
        rows = _running(rows, names, p.op, fn, ranges)
    return rows.where("_src = 1 and _seen is not null").select("_row.*", "_seen")


def inclusion(terms: list[list[tuple]]) -> list[tuple[int, list[tuple]]]:
    """Terms with signs that count each pair of a disjunction once, by inclusion and exclusion."""
    out = []
    for n in range(1, len(terms) + 1):
        for some in combinations(terms, n):
            out.append(((-1) ** (n + 1), list({(p.op, p.eps, a, b): (p, a, b) for term in some for p, a, b in term}.values())))
    return out


def disjoint(terms: list[list[tuple]]) -> list[list[tuple]] | None:
    """Terms of which a pair of keys without nulls meets at most one; None if that takes more than inclusion and exclusion, or a band's opposite."""
    out: list[list[tuple]] = []
    for k, term in enumerate(terms):
        pieces = [term]
        for earlier in terms[:k]:
            made = []
            for piece in pieces:
                rest = [x for x in earlier if x not in piece]
                if any(p.op == "band" for p, _, _ in rest):
                    return None
                for n, (p, a, b) in enumerate(rest):  # the first n hold and the next one does not
                    opposite = (Compare(NEGATE[p.op], p.left, p.right), a, b)
                    if (p, a, b) not in piece and not any((Compare(NEGATE[q.op], q.left, q.right), x, y) in piece for q, x, y in rest[:n] if q.op != "band"):
                        made.append(piece + [x for x in (*rest[:n], opposite) if x not in piece])
            pieces = made
        out += pieces
    return out if len(out) < 2 ** len(terms) - 1 else None


def without_nulls(s: DataFrame, t: DataFrame, terms: list[list[tuple]]) -> bool:
    """Whether no key is null, by a scan of each side."""
    for df, columns in ((s, {a for term in terms for _, a, _ in term}), (t, {b for term in terms for _, _, b in term})):
        if df.agg(F.max(reduce(lambda x, y: x | y, [F.col(c).isNull() for c in sorted(columns)]))).first()[0]:
            return False
    return True


def _numeric(df: DataFrame, column: str) -> bool:
    return dict(df.dtypes)[column].startswith(("bigint", "int", "smallint", "tinyint", "double", "float", "decimal", "date", "timestamp"))


def expands(terms: list[list[tuple]]) -> bool:
    """Whether a source can have several rows on the way."""
    return len(terms) > 1 or any(len(hard := [p for p, _, _ in term if p.op != "="]) > 1 or any(p.op == "band" for p in hard) for term in terms)


def placed(df: DataFrame, order: str, name: str, staging: Staging, tag: str) -> DataFrame:
    """``df`` as a written table with a column that numbers its rows in an order (with gaps)."""
    n = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return staging.save(df.repartitionByRange(n, order).sortWithinPartitions(order).withColumn(name, F.monotonically_increasing_id()), f"{tag}-placed")


def by_places(t: DataFrame, places: str) -> tuple[DataFrame, DataFrame]:
    """``t`` with places for values, and (place, value)."""
    return t.drop("val").withColumnRenamed(places, "val"), t.select(F.col(places).alias("_seen"), F.col("val").alias("_value"))


def fold(s: DataFrame, t: DataFrame, terms: list[list[tuple[Compare, str, str]]], fn: str, out: str, staging: Staging, tag: str, ranges: int | None | Callable = None, places: str | None = None, known: Values | None = None) -> DataFrame:
    """``s`` (rid and other columns) with ``out``: min or sum of ``t.val`` over joining targets; sources without one drop out.

    ``terms``: comparisons with the key columns of s and of t. ``ranges``: key ranges of a
    partition, or a function that gives them for a term; by default partitions above
    ``SPLIT`` rows are cut. ``places``: a column of a written ``t`` that numbers its rows in
    the order of ``val``. Ids are unique and not null.
    """
    columns = s.columns
    if any(isinstance(p, Opaque) for term in terms for p, _, _ in term):
        raise ValueError("opaque predicates can't be folded")
    known = known or Values(staging)
    signed = [(1, term) for term in terms]
    if fn == "sum" and len(terms) > 1:
        apart = disjoint(terms)
        signed = [(1, term) for term in apart] if apart is not None and without_nulls(s, t, terms) else inclusion(terms)
    several = expands([term for _, term in signed])
    t = t.select(*dict.fromkeys(b for _, term in signed for _, _, b in term), "val", *([places] if places else []))
    values = None
    if several and fn == "min":
        t, values = by_places(t, places) if places else by_places(placed(t, "val", "_n", staging, tag), "_n")
    elif places:
        t = t.drop(places)
    carried = [] if several else [c for c in columns if c != "rid"]
    lean = s.select("rid", *dict.fromkeys(a for _, term in signed for _, a, _ in term)) if several else s
    total = None
    for k, (sign, term) in enumerate(signed):
        cut = ranges(term) if callable(ranges) else ranges if ranges is not None else ranges_for(lean, t, term)
        one = _term_fold(lean, t, term, fn, staging, f"{tag}-{k}", cut, carried, known)
        one = one.withColumn("_seen", -F.col("_seen")) if sign < 0 else one
        total = one if total is None else total.unionByName(one)
    if not several:
        return total.select(*columns, F.col("_seen").alias(out))
    total = total.groupBy("rid").agg(_agg(fn, F.col("_seen")).alias("_seen"))
    if values is not None:
        total = total.join(merged(values), "_seen").select("rid", F.col("_value").alias("_seen"))
    return s.join(merged(total), "rid").select(*columns, F.col("_seen").alias(out))


def ranges_for(s: DataFrame, t: DataFrame, term: list[tuple]) -> int:
    """Key ranges that a term's partitions need, from the largest groups under its equalities."""
    equal = [(a, b) for p, a, b in term if p.op == "="]
    if len(equal) == len(term):
        return 1
    return RANGES if largest_group(s, [a for a, _ in equal]) + largest_group(t, [b for _, b in equal]) > SPLIT else 1
