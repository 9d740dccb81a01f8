"""Removal of byte strings that repeat anywhere in the corpus.

Every byte covered by a string of ``length`` bytes that also starts elsewhere (in any
document, the same included) is removed; strings never cross documents and are judged on
the input.

Parsing. The triggers of a prefix-free parse are positions whose rolling hash of ``gram``
bytes is the smallest of a window of ``length``: each string of that length has a
trigger, at the same place in all its occurrences, so equal strings meet at equal
triggers whatever surrounds them. The dictionary holds what lies around a trigger, as far
as a string with that trigger can reach; the parse is the list of triggers.

Order. Of the suffix order of the corpus only one thing is needed: which suffixes share
``length`` bytes with a neighbour. Those share a trigger, so the order is made per trigger
gram. Dictionary entries that occur twice repeat as a whole and need no further look. For
the others, where some string is shared and the surroundings differ, the strings at the
trigger are ranked by hash together with one copy of each repeated entry.

Nulls: a null text is empty; null ids stay null. Equal texts are one class; all bytes of
a text that occurs twice are removed if it has ``length`` bytes. Empty table: empty
result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import groups, textkit
from .workspace import Workspace

LENGTH, GRAM = 400, 64
#: Bytes of a text that are parsed at once; pieces overlap by a string.
PIECE = 1 << 22
#: Strings that are ranked at once.
STRINGS = 1 << 20
#: Surroundings of one gram that a task ranks; beyond it their strings are dealt out. Costs only, same results.
HOT = 1 << 16
_U = np.uint64
_POSITION = _U((1 << 24) - 1)


def sliding_min(a: np.ndarray, w: int) -> np.ndarray:
    """The minimum of each run of ``w`` values."""
    n = len(a) - w + 1
    blocks = np.full(-(-len(a) // w) * w, np.iinfo(np.uint64).max, np.uint64)
    blocks[: len(a)] = a
    blocks = blocks.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).reshape(-1)
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])


def triggers(data: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions, gram hashes and surroundings hashes of the triggers of one text.

    The surroundings reach from ``length - gram`` bytes before to ``length`` bytes after
    the trigger, cut at the text's ends.
    """
    at, grams, around = [], [], []
    n = len(data)
    for a in range(0, max(1, n - length + 1), PIECE):
        # a piece also sees what lies around the triggers of its strings
        low, high = max(0, a - length), min(n, a + PIECE + 2 * length)
        part = data[low:high]
        if len(part) < length:
            continue
        acc = textkit.prefix_hash(textkit._TABLE[part])
        back = textkit.powers(len(part) + 1)[1]
        m = len(part) - gram + 1
        h = textkit.mix((acc[gram:] - acc[:m]) * back[:m])
        key = (h & ~_POSITION) | np.arange(m, dtype=np.uint64)
        first, last = a - low, min(a + PIECE, n - length + 1) - low
        least = sliding_min(key[first : last + length - gram], length - gram + 1)
        x = (least[np.concatenate([[True], least[1:] != least[:-1]])] & _POSITION).astype(np.int64)
        x = np.unique(x)
        lo, hi = np.maximum(x - (length - gram), 0), np.minimum(x + length, len(part))
        whole = textkit.mix((acc[hi] - acc[lo]) * back[lo] + textkit.mix(((x - lo) << 32 | (hi - lo)).astype(np.uint64)))
        at.append(x + low)
        grams.append(h[x])
        around.append(whole)
    if not at:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    x, first = np.unique(np.concatenate(at), return_index=True)
    return x, np.concatenate(grams)[first], np.concatenate(around)[first]


def text_name(raw: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(raw, digest_size=8).digest(), "big", signed=True)


def _texts(column: pa.Array):
    """(bytes as array, bytes) of each text."""
    for part in textkit.slices(column):
        data, off = textkit.utf8(part)
        for i in range(len(part)):
            one = data[off[i] : off[i + 1]]
            yield one, one.tobytes()


def parse(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(gram, around, cls, pos, size): the triggers of each class of texts, once per task."""
    names = ("gram", "around", "cls", "pos", "size")
    schema = pa.schema([(n, pa.int64()) for n in names])

    def find(batches):
        seen: set[int] = set()
        for batch in batches:
            parts, held = [], 0
            for data, raw in _texts(batch.column(0)):
                if len(data) < length or (name := text_name(raw)) in seen:
                    continue
                seen.add(name)
                x, g, w = triggers(data, length, gram)
                parts.append((textkit.signed(g), textkit.signed(w), np.full(len(x), name), x, np.full(len(x), len(data))))
                held += len(x)
                if held > 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts, strict=True)], schema=schema)
                    parts, held = [], 0
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts, strict=True)], schema=schema)

    return docs.select("text").mapInArrow(textkit.frugal(find), ", ".join(f"{n} long" for n in names))


def strings_at(gram_of: np.ndarray, texts: list[bytes], left: np.ndarray, ds: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(surrounding, start in it, hash) of the strings that begin ``ds`` bytes before the trigger.

    ``left``: bytes of a surrounding before its trigger. Gram and offset are part of the hash.
    """
    span, offsets = 2 * length - gram, length - gram
    size = np.array([len(t) for t in texts])
    rows = max(1, STRINGS // (2 * span))
    power, back = textkit.powers(span + 1)
    hashes = np.zeros((len(texts), len(ds)), np.uint64)
    valid = (ds[None, :] <= left[:, None]) & (length - ds[None, :] <= (size - left)[:, None])
    for a in range(0, len(texts), rows):
        b = min(a + rows, len(texts))
        padded = np.zeros((b - a, span), np.uint8)
        for i in range(a, b):
            shift = offsets - int(left[i])  # triggers stand under each other
            padded[i - a, shift : shift + size[i]] = np.frombuffer(texts[i], np.uint8)
        acc = np.zeros((b - a, span + 1), np.uint64)
        np.cumsum(textkit._TABLE[padded] * power[:span], axis=1, out=acc[:, 1:])
        starts = offsets - ds
        hashes[a:b] = textkit.mix((acc[:, starts + length] - acc[:, starts]) * back[starts] + gram_of[a:b, None].view(np.uint64) * _U(0x9E3779B97F4A7C15) + textkit.mix(ds.astype(np.uint64) + _U(1)))
    row, col = np.nonzero(valid)
    return row, left[row] - ds[col], hashes[row, col]


def rank_strings(gram_of: np.ndarray, texts: list[bytes], left: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """For each surrounding, the first and last start of a string that another one of the same gram shares; -1 if none."""
    first, last = np.full(len(texts), -1, np.int64), np.full(len(texts), -1, np.int64)
    step = max(1, STRINGS // max(1, len(texts)))
    for d0 in range(0, length - gram + 1, step):
        row, start, hashes = strings_at(gram_of, texts, left, np.arange(d0, min(d0 + step, length - gram + 1)), length, gram)
        order = np.argsort(hashes, kind="stable")
        h = hashes[order]
        same = h[1:] == h[:-1]
        again = np.zeros(len(h), bool)
        again[1:] |= same
        again[:-1] |= same
        r, start = row[order][again], start[order][again]
        low, high = np.full(len(texts), 1 << 40), np.full(len(texts), -1)
        np.minimum.at(low, r, start)
        np.maximum.at(high, r, start)
        hit = high >= 0
        first[hit] = np.where(first[hit] < 0, low[hit], np.minimum(first[hit], low[hit]))
        last[hit] = np.maximum(last[hit], high[hit])
    return first, last


def rank_dealt(around: DataFrame, work: Workspace, length: int, gram: int) -> DataFrame:
    """(cls, a, b) as from ``rank_strings``, for grams with more surroundings than one task should hold.

    Every string is a row of its hash, and Spark counts them: a hash that all have is
    summed up where it is made, and the join deals its rows anew.
    """
    schema = pa.schema([("h", pa.int64()), ("cls", pa.int64()), ("pos", pa.int64()), ("at", pa.int64()), ("single", pa.bool_())])

    def spread(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 1024):
                g, cls, pos, low = (batch.column(k).slice(i, 1024).to_numpy() for k in range(4))
                row, start, h = strings_at(g, batch.column(5).slice(i, 1024).to_pylist(), pos - low, np.arange(length - gram + 1), length, gram)
                single = batch.column(4).slice(i, 1024).to_numpy(zero_copy_only=False)
                for a in range(0, len(row), 1 << 16):
                    r = row[a : a + (1 << 16)]
                    yield pa.RecordBatch.from_pydict({"h": textkit.signed(h[a : a + (1 << 16)]), "cls": cls[r], "pos": pos[r], "at": low[r] + start[a : a + (1 << 16)], "single": single[r]}, schema=schema)

    rows = work.save(around.mapInArrow(textkit.frugal(spread), "h long, cls long, pos long, at long, single boolean"), "strings")
    place = F.struct("cls", "pos")
    twice = rows.groupBy("h").agg(F.min(place).alias("one"), F.max(place).alias("other")).where("one <> other").select("h")
    hit = rows.where("single").join(twice, "h", "left_semi").groupBy("cls", "pos").agg(F.min("at").alias("a"), (F.max("at") + length).alias("b"))
    return hit.select("cls", "a", "b")


def removed_ranges(docs: DataFrame, work: Workspace, length: int, gram: int) -> tuple[DataFrame, DataFrame]:
    """(row, cls, size) of all rows and (cls, a, b), ranges of bytes to remove in each class of texts."""
    spark = docs.sparkSession
    partitions = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    reach = length - gram

    def describe(batches):
        for batch in batches:
            found = [(text_name(raw), len(raw)) for _, raw in _texts(batch.column(1))]
            yield pa.RecordBatch.from_pydict({"row": batch.column(0), "cls": [f[0] for f in found], "size": [f[1] for f in found]}, schema=pa.schema([("row", pa.int64()), ("cls", pa.int64()), ("size", pa.int64())]))

    rows = work.save(docs.select(textkit.row_key(), "text").mapInArrow(textkit.frugal(describe), "row long, cls long, size long"), "rows")
    classes = rows.groupBy("cls").agg(F.min("row").alias("row"), F.count(F.lit(1)).alias("n"), F.max("size").alias("size"))
    classes = work.save(classes.where(F.col("size") >= length), "classes")
    whole = classes.where("n > 1").select("cls", F.lit(0).cast("long").alias("a"), F.col("size").alias("b"))

    place = F.struct("cls", "pos")
    parsed = work.save(parse(docs, length, gram), "parse")
    # a gram in all documents is counted where it is read, and its rows are dealt anew by the join
    twice = parsed.groupBy("gram").agg(F.min(place).alias("one"), F.max(place).alias("other")).where("one <> other").select("gram")
    shared = work.save(parsed.join(twice, "gram", "left_semi").distinct(), "triggers")
    work.drop("parse")
    entries = shared.groupBy("gram", "around").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("cls", "pos", "size")).alias("at"))
    entries = work.save(entries, "entries")
    low, high = F.greatest(F.lit(0), F.col("pos") - reach), F.least(F.col("size"), F.col("pos") + length)
    repeated = shared.join(entries.where("n > 1").select("gram", "around"), ["gram", "around"], "left_semi").select("cls", low.alias("a"), high.alias("b"))

    open_grams = entries.groupBy("gram").agg(F.min("n").alias("least"), F.count(F.lit(1)).alias("k")).where("least = 1 and k > 1").select("gram", (F.col("k") > HOT).alias("hot"))
    open_grams = work.save(open_grams, "open")

    def asked_of(grams):
        per_text = entries.join(grams.select("gram"), "gram", "left_semi").select("gram", "at.*", "n").groupBy("cls").agg(F.collect_list(F.struct("gram", "pos", "n")).alias("asked"))
        per_text = per_text.join(classes.select("cls", "row"), "cls")
        return textkit.by_row(docs).join(per_text, "row").select("cls", "text", "asked")

    schema = pa.schema([("gram", pa.int64()), ("cls", pa.int64()), ("pos", pa.int64()), ("low", pa.int64()), ("single", pa.bool_()), ("around", pa.binary())])

    def cut(batches):
        for batch in batches:
            at = 0
            for _, raw in _texts(batch.column(1)):
                cls, wanted = batch.column(0)[at].as_py(), batch.column(2)[at].as_py()
                at += 1
                if text_name(raw) != cls:  # another text of this id
                    continue
                for a in range(0, len(wanted), 10_000):
                    some = wanted[a : a + 10_000]
                    lows = [max(0, w["pos"] - reach) for w in some]
                    yield pa.RecordBatch.from_pydict({"gram": [w["gram"] for w in some], "cls": [cls] * len(some), "pos": [w["pos"] for w in some], "low": lows, "single": [w["n"] == 1 for w in some], "around": [raw[x : w["pos"] + length] for x, w in zip(lows, some, strict=True)]}, schema=schema)

    around_of = lambda grams: asked_of(grams).mapInArrow(textkit.frugal(cut), "gram long, cls long, pos long, low long, single boolean, around binary")
    hot = open_grams.where("hot")
    ordered = around_of(open_grams.where("not hot")).repartition(partitions, "gram").sortWithinPartitions("gram", "cls", "pos")

    def rank(batches):
        def ranges(table):
            g, cls, pos, low = (table.column(k).to_numpy() for k in ("gram", "cls", "pos", "low"))
            # an id that stands for a text twice brings its entries twice
            fresh = np.concatenate([[True], (g[1:] != g[:-1]) | (cls[1:] != cls[:-1]) | (pos[1:] != pos[:-1])])
            table, g, cls, pos, low = table.filter(pa.array(fresh)), g[fresh], cls[fresh], pos[fresh], low[fresh]
            first, last = rank_strings(g, table.column("around").to_pylist(), pos - low, length, gram)
            hit = (first >= 0) & table.column("single").to_numpy()
            return pa.RecordBatch.from_pydict({"cls": cls[hit], "a": (low + first)[hit], "b": (low + last + length)[hit]}, schema=pa.schema([("cls", pa.int64()), ("a", pa.int64()), ("b", pa.int64())]))

        for table, bounds in groups.runs(batches, 1):
            a = 0
            while a < len(bounds) - 1:  # whole groups, about as many rows as are ranked at once
                b = max(a + 1, int(np.searchsorted(bounds, bounds[a] + STRINGS // (reach + 1), "right")) - 1)
                yield ranges(table.slice(int(bounds[a]), int(bounds[b] - bounds[a])))
                a = b

    partly = ordered.mapInArrow(textkit.frugal(rank), "cls long, a long, b long")
    if not hot.isEmpty():
        partly = partly.unionByName(rank_dealt(around_of(hot), work, length, gram))
    found = work.save(partly.unionByName(repeated).unionByName(whole), "ranges")
    return rows, found


def remove(docs: DataFrame, length: int = LENGTH, gram: int | None = None, texts: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256; with ``texts`` also n_kept and the kept ``text``.

    Spans may cut a character; what is left of it is U+FFFD in ``text``, not in the digest.
    """
    gram = gram or max(1, length * 4 // 25)
    docs = docs.select("doc_id", "text")
    work = Workspace(docs.sparkSession, "repeats")
    rows, found = removed_ranges(docs, work, length, gram)
    per_class = found.groupBy("cls").agg(F.collect_list(F.struct("a", "b")).alias("spans"))
    # by row key, so that the text goes over the network once; ids of several texts are told apart by class
    named = rows.select("row", "cls").distinct().join(per_class, "cls").groupBy("row").agg(F.collect_list(F.struct("cls", "spans")).alias("known"))
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())] + [("n_kept", pa.int64()), ("text", pa.string())] * texts)

    def apply(batches):
        for batch in batches:
            ids, out = batch.column(0).to_pylist(), {k: [] for k in schema.names}
            for i, (data, raw) in enumerate(_texts(batch.column(1))):
                known = batch.column(2)[i].as_py() or []
                name = text_name(raw) if known else None
                spans = sorted((s["a"], s["b"]) for k in known if k["cls"] == name for s in k["spans"])
                kept, runs, end = [], 0, 0
                for a, b in spans:
                    if a > end or not runs:  # touching runs are one
                        kept.append(raw[end:a])
                        runs += 1
                    end = max(end, b)
                kept.append(raw[end:])
                left = b"".join(kept)
                values = (ids[i], len(raw), len(raw) - len(left), runs, hashlib.sha256(left).hexdigest()) + ((len(left), left.decode("utf-8", "replace")) if texts else ())
                for key, value in zip(out, values, strict=True):
                    out[key].append(value)
            yield pa.RecordBatch.from_pydict(out, schema=schema)

    rows = docs.select("doc_id", textkit.row_key(), "text").join(named, "row", "left").select("doc_id", "text", "known")
    return rows.mapInArrow(textkit.frugal(apply), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", n_kept long, text string" if texts else ""))
