"""Token-ID output: frequency-ranked ids in byte-aligned variable-length coding.

Ids are replaced by their rank in the corpus (0 for the most frequent), and a rank is
written with one to four bytes. The two-bit lengths stand apart in control bytes, four
ids to a byte, so a reader finds all lengths of a segment by one numpy table lookup on
the control bytes and all values by one gather per byte position.

Segment file: magic, counts of documents, ids, control and data bytes; document ids,
their null marks and token counts; control bytes; data bytes; CRC-32 of all that. The
ranks are a file of little-endian 32-bit ids beside the segments.

Text is cut at spaces and line feeds before it is encoded. The tokenizer given removes
white space before it looks for tokens, so that the cut changes nothing, and each
distinct chunk is encoded once per worker. ``chunked=False`` encodes whole texts, for
tokenizers where that does not hold. Texts are encoded once, in the order of doc_id, and
ids are counted as they are made. With ``waves``, ranges of doc_id are sorted and encoded
one after the other, so that no more than one of them is on disk as text; each reads the
table again.

Nulls: a null text is empty, so that its row has the end id only; null doc_ids come
first. Rows with equal doc_id follow each other, in the order of their texts. Empty
table: no segment, empty result.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import files, partials, textkit
from .workspace import Workspace

MAGIC = b"RANKVB01"
#: Ids of a segment; a longer document makes a longer one.
SEGMENT_IDS = 1 << 20
#: Distinct chunks, and distinct pieces of chunks, kept per worker in each of two generations.
CACHE = 200_000
_SIGNS = frozenset(".,:;!?*|#%&$()-")
_encoders: dict[str, Encoder] = textkit.remembered("encoders")


class Remembered(dict):
    """Results of a function by argument; of two generations, the older one is forgotten by ``trim``."""

    def __init__(self, make):
        super().__init__()
        self.make, self.old = make, {}

    def __missing__(self, key: str) -> bytes:
        found = self.old.get(key)
        if found is None:
            found = self.make(key)
        self[key] = found
        return found

    def trim(self) -> None:
        if len(self) > CACHE:
            self.old = dict(self)
            self.clear()


class Encoder:
    """A tokenizer that encodes each distinct chunk of text once.

    Where the file describes byte-level BPE behind a lower-casing normalizer and a
    pattern, chunks below U+0250 go from the pattern's pieces straight to the library's
    BPE model; all others go through its whole pipeline.
    """

    def __init__(self, path: str):
        import json

        import regex
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as src:
            spec = json.load(src)
        self.tok = Tokenizer.from_file(path)
        self.chunks, self.lower, self.pieces = Remembered(self._chunk), Remembered(self._lower), Remembered(self._piece)
        names = [x["type"] for x in (spec.get("normalizer") or {}).get("normalizers", [])], [x["type"] for x in (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])]
        self.pattern = None
        if names == (["NFC", "Replace", "Lowercase"], ["Split", "ByteLevel"]) and spec["model"]["type"] == "BPE" and not spec.get("post_processor"):
            split, level = spec["pre_tokenizer"]["pretokenizers"]
            if split["behavior"] == "Removed" and split["invert"] and not level["add_prefix_space"] and not level["use_regex"]:
                self.pattern = regex.compile(split["pattern"]["Regex"])
                self.plain = regex.compile("[\\x00-\u024f]*")
                seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
                self.byte_chars = {b: chr(b) for b in seen} | {b: chr(256 + i) for i, b in enumerate(x for x in range(256) if x not in seen)}
                self.marks = [t["content"] for t in spec["added_tokens"]]

    def _piece(self, piece: str) -> bytes:
        mapped = piece if piece.isascii() else piece.encode().decode("latin-1").translate(self.byte_chars)
        return array("I", [t.id for t in self.tok.model.tokenize(mapped)]).tobytes()

    def _plain(self, text: str) -> bool:
        """Whether pieces of this text can go straight to the model, in lower case."""
        return self.pattern is not None and ("<" not in text or not any(m in text for m in self.marks)) and (text.isascii() or self.plain.fullmatch(text) is not None)

    def _chunk(self, chunk: str) -> bytes:
        return self._lower(chunk.lower()) if self._plain(chunk) else array("I", self.tok.encode(chunk, add_special_tokens=False).ids).tobytes()

    def _lower(self, chunk: str) -> bytes:
        """A plain chunk in lower case; letters, or letters and one sign, are what the pattern would find."""
        if chunk.isalpha():
            return self._piece(chunk)
        head, sign = chunk[:-1], chunk[-1:]
        if sign in _SIGNS and head.isalpha():
            return self.lower[head] + self.pieces[sign]
        return b"".join(map(self.pieces.__getitem__, self.pattern.findall(chunk)))

    def encode(self, column: pa.Array, end_id: int | None = 1, chunked: bool = True) -> Iterator[np.ndarray]:
        """The uint32 ids of each text, with the end id."""
        end = b"" if end_id is None else np.uint32(end_id).tobytes()
        for part in textkit.slices(column, 1 << 21):
            texts = [t or "" for t in part.to_pylist()]
            if not chunked:
                for made in self.tok.encode_batch(texts, add_special_tokens=False):
                    yield np.frombuffer(array("I", made.ids).tobytes() + end, np.uint32)
                continue
            for t in texts:
                known, t = (self.lower, t.lower()) if "<" not in t and self._plain(t) else (self.chunks, t)
                yield np.frombuffer(b"".join(map(known.__getitem__, t.replace("\n", " ").split(" "))) + end, np.uint32)
            for known in (self.chunks, self.lower, self.pieces):
                known.trim()


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def pack(ranks: np.ndarray) -> tuple[bytes, bytes]:
    """Control and data bytes of uint32 values."""
    r = np.ascontiguousarray(ranks, "<u4")
    code = (r > 0xFF).astype(np.uint8) + (r > 0xFFFF) + (r > 0xFFFFFF)
    keep = np.arange(4)[None, :] <= code[:, None]
    four = np.zeros(-(-len(r) // 4) * 4, np.uint8)
    four[: len(r)] = code
    four = four.reshape(-1, 4)
    control = four[:, 0] | four[:, 1] << 2 | four[:, 2] << 4 | four[:, 3] << 6
    return control.astype(np.uint8).tobytes(), r.view(np.uint8).reshape(-1, 4)[keep].tobytes()


_LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3).astype(np.uint8) + 1


def unpack(control: bytes, data: bytes, n: int) -> np.ndarray:
    """Values back from ``pack``; raises ValueError if the bytes do not fit together."""
    if len(control) != -(-n // 4):
        raise ValueError("control bytes do not match the count")
    length = _LENGTHS[np.frombuffer(control, np.uint8)].reshape(-1)[:n]
    ends = np.cumsum(length, dtype=np.int64)
    if (int(ends[-1]) if n else 0) != len(data):
        raise ValueError("data bytes do not match the lengths")
    start = ends - length
    src = np.frombuffer(data, np.uint8)
    out = src[start].astype(np.uint32)
    k, more = 1, np.flatnonzero(length > 1)
    while len(more):  # the longer a value, the fewer there are
        out[more] |= src[start[more] + k].astype(np.uint32) << np.uint32(8 * k)
        k += 1
        more = more[length[more] > k]
    return out


def write_segment(doc_ids: list, counts: list[int], ranks: np.ndarray) -> bytes:
    control, data = pack(ranks)
    known = np.array([d is not None for d in doc_ids], np.uint8)
    body = b"".join(
        (
            np.array([len(doc_ids), len(ranks), len(control), len(data)], "<u8").tobytes(),
            np.array([d if d is not None else 0 for d in doc_ids], "<i8").tobytes(),
            known.tobytes(),
            np.array(counts, "<u8").tobytes(),
            control,
            data,
        )
    )
    return MAGIC + body + np.uint32(zlib.crc32(body)).tobytes()


def read_segment(raw: bytes) -> tuple[list, np.ndarray, np.ndarray]:
    """doc_ids, token counts and ranks of a segment."""
    if raw[:8] != MAGIC:
        raise ValueError("not a segment")
    body = raw[8:-4]
    if zlib.crc32(body) != int(np.frombuffer(raw[-4:], "<u4")[0]):
        raise ValueError("checksum differs")
    n_docs, n_ids, n_control, n_data = (int(x) for x in np.frombuffer(body[:32], "<u8"))
    at = 32
    ids = np.frombuffer(body, "<i8", n_docs, at).tolist()
    at += 8 * n_docs
    known = np.frombuffer(body, np.uint8, n_docs, at).tolist()
    at += n_docs
    counts = np.frombuffer(body, "<u8", n_docs, at).astype(np.int64)
    at += 8 * n_docs
    ranks = unpack(body[at : at + n_control], body[at + n_control : at + n_control + n_data], n_ids)
    if int(counts.sum()) != n_ids:
        raise ValueError("counts differ")
    return [d if k else None for d, k in zip(ids, known, strict=True)], counts, ranks


def _blocks(docs: DataFrame, path: str, end_id: int, chunked: bool, partitions: int, first: int = 0) -> DataFrame:
    """Texts in the order of doc_id, encoded: a row per future segment, and rows of negative numbers with pieces of a task's counts of ids.

    ``data`` has two bytes an id where they suffice for all of a row, else four; parts are numbered from ``first``.
    """
    limit = SEGMENT_IDS
    schema = pa.schema([("part", pa.int32()), ("number", pa.int32()), ("n_ids", pa.int64()), ("docs", pa.list_(pa.int64())), ("counts", pa.list_(pa.int64())), ("data", pa.binary())])

    def encode(batches):
        from pyspark import TaskContext

        part, number = first + TaskContext.get().partitionId(), 0
        ids, rows, held = [], [], 0
        total = np.zeros(1 << 16, np.int64)

        def block():
            nonlocal total
            found = np.concatenate(rows)
            n = np.bincount(found, minlength=len(total))
            n[: len(total)] += total
            total = n
            data = found.astype("<u2" if len(found) and found.max() < 1 << 16 else "<u4").tobytes()
            return pa.RecordBatch.from_pydict({"part": [part], "number": [number], "n_ids": [held], "docs": [ids], "counts": [[len(r) for r in rows]], "data": [data]}, schema=schema)

        for batch in batches:
            for doc, found in zip(batch.column(0).to_pylist(), encoder(path).encode(batch.column(1), end_id, chunked), strict=True):
                ids.append(doc)
                rows.append(found)
                held += len(found)
                if held >= limit:
                    yield block()
                    number, ids, rows, held = number + 1, [], [], 0
        if ids:
            yield block()
        for piece, data in enumerate(partials.rows(np.pad(total, (0, -len(total) % partials.SLICE)), part)["part"]):
            yield pa.RecordBatch.from_pydict({"part": [part], "number": [-1 - piece], "n_ids": [0], "docs": [None], "counts": [None], "data": [data]}, schema=schema)

    ordered = docs.select("doc_id", "text").repartitionByRange(partitions, "doc_id").sortWithinPartitions("doc_id", "text")
    return ordered.mapInArrow(textkit.frugal(encode, "encoders"), "part int, number int, n_ids long, docs array<long>, counts array<long>, data binary")


def id_counts(blocks: DataFrame) -> np.ndarray:
    """How often each id stands in the corpus, end ids included."""
    pieces = blocks.where("number < 0").select((-1 - F.col("number")).alias("piece"), F.pmod("part", F.lit(partials.SALTS)).alias("salt"), F.col("data").alias("part"))
    last = pieces.agg(F.max("piece")).first()[0]
    return partials.collect(pieces, 0 if last is None else (last + 1) * partials.SLICE)


def _ranges(docs: DataFrame, waves: int) -> list[DataFrame]:
    """Rows dealt into ranges of doc_id of about equal counts, in ascending order, nulls in the first."""
    cuts = sorted({int(x) for x in docs.approxQuantile("doc_id", [k / waves for k in range(1, waves)], 0.02)}) if waves > 1 else []
    doc_id, out = F.col("doc_id"), []
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        part = docs if high is None else docs.where(doc_id < high if low is not None else doc_id.isNull() | (doc_id < high))
        out.append(part if low is None else part.where(doc_id >= low))
    return out


def write_ids(docs: DataFrame, work: Workspace, path: str, end_id: int = 1, chunked: bool = True, partitions: int | None = None, waves: int = 1) -> DataFrame:
    """Writes the corpus as segments; returns the manifest.

    The manifest has a row per segment: uri, part and number (their order is that of
    doc_id), n_ids, start (ids in all segments before), ranks_uri.
    """
    spark = docs.sparkSession
    partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranges = _ranges(docs, waves)
    each = max(1, -(-partitions // len(ranges)))
    blocks = [work.save(_blocks(x, path, end_id, chunked, each, k * each), f"blocks{k}", "zstd") for k, x in enumerate(ranges)]
    # a number per id of the vocabulary, whatever the corpus
    total = id_counts(reduce(DataFrame.unionByName, blocks))
    order = np.flatnonzero(total).astype(np.uint32)
    order = order[np.argsort(-total[order], kind="stable")]
    rank_of = np.zeros(int(order.max()) + 1 if len(order) else 1, np.uint32)
    rank_of[order] = np.arange(len(order), dtype=np.uint32)
    files_at = work.at("segments")
    ranks_uri = files.put(files_at, order.astype("<u4").tobytes(), ".ranks")
    shared = spark.sparkContext.broadcast(rank_of)

    def write(batches):
        table, schema = shared.value, pa.schema([("uri", pa.string()), ("part", pa.int32()), ("number", pa.int32()), ("n_ids", pa.int64())])
        for batch in batches:
            for row in batch.to_pylist():
                ids = np.frombuffer(row["data"], "<u2" if len(row["data"]) == 2 * row["n_ids"] else "<u4")
                raw = write_segment(row["docs"], row["counts"], table[ids])
                yield pa.RecordBatch.from_pydict({"uri": [files.put(files_at, raw, ".seg")]} | {c: [row[c]] for c in ("part", "number", "n_ids")}, schema=schema)

    written = []
    for k, x in enumerate(blocks):
        written.append(work.save(x.where("number >= 0").mapInArrow(textkit.frugal(write, "encoders"), "uri string, part int, number int, n_ids long"), f"manifest{k}"))
        work.drop(f"blocks{k}")
    manifest = reduce(DataFrame.unionByName, written)
    before = Window.orderBy("part", "number").rowsBetween(Window.unboundedPreceding, 0)
    return manifest.withColumn("start", F.sum("n_ids").over(before) - F.col("n_ids")).withColumn("ranks_uri", F.lit(ranks_uri))


def read_ids(manifest: DataFrame, digest_only: bool = True) -> DataFrame:
    """Decodes the segments of a manifest: doc_id, start, n_tokens, ids_crc32 (and the ids themselves)."""
    spark = manifest.sparkSession
    kept: dict[str, np.ndarray] = {}

    def read(batches):
        for batch in batches:
            for row in batch.to_pylist():
                if row["ranks_uri"] not in kept:
                    kept[row["ranks_uri"]] = np.frombuffer(files.get(row["ranks_uri"]), "<u4")
                docs, counts, ranks = read_segment(files.get(row["uri"]))
                ids = kept[row["ranks_uri"]][ranks]
                ends = np.cumsum(counts)
                raw = memoryview(np.ascontiguousarray(ids, "<u4")).cast("B")
                out = {"doc_id": docs, "start": (ends - counts + row["start"]).tolist(), "n_tokens": counts.tolist(), "ids_crc32": [zlib.crc32(raw[4 * int(e - c) : 4 * int(e)]) for c, e in zip(counts, ends, strict=True)]}
                fields = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())]
                if not digest_only:
                    out["ids"] = [ids[e - c : e].astype(np.int64) for c, e in zip(counts, ends, strict=True)]
                    fields.append(("ids", pa.list_(pa.int64())))
                yield pa.RecordBatch.from_pydict(out, schema=pa.schema(fields))

    # a task per core and some more is enough: a segment is read at a time
    most = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
    return manifest.repartition(max(1, min(manifest.count(), most)), "uri").mapInArrow(textkit.frugal(read, "encoders"), "doc_id long, start long, n_tokens long, ids_crc32 long" + ("" if digest_only else ", ids array<long>"))


def token_report(docs: DataFrame, path: str, end_id: int = 1, waves: int = 1) -> DataFrame:
    """Writes the ids of all texts and reads the files back: doc_id, start, n_tokens, ids_crc32."""
    work = Workspace(docs.sparkSession, "tokenids")
    return read_ids(write_ids(docs, work, path, end_id, waves=waves))
