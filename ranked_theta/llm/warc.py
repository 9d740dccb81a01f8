"""WARC archives in Zstandard: one frame per record, dictionary in a leading skippable frame.

Writing: each task trains a dictionary on the first pages that it gets, writes it into
a skippable frame and then one frame per record. Of pages with equal payloads (SHA-1
and length) the one with the largest page_id is a response and the others are revisits
that point to it. Reading: the skippable frame gives the dictionary, frame lengths are
found from the block headers, each frame is decoded alone, and version line, header
fields, Content-Length, record end and payload digest are checked.

Nulls: a null html is an empty payload; a null page_id counts as smaller than any (all
null: all responses); a null url gives a urn as target. Repeated rows with the largest
page_id are all responses. Empty table: no archive, empty result.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import files
from .workspace import Workspace

SKIPPABLE = 0x184D2A5D
#: Payload bytes after which a task begins a new archive.
ARCHIVE_BYTES = 1 << 26
#: Bytes of pages that a dictionary is trained on, and its size.
SAMPLE_BYTES, DICTIONARY_BYTES = 1 << 20, 1 << 15
DATE = "2020-01-01T00:00:00Z"
_NAMES = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")
_END = b"\r\n\r\n"


class BadArchive(ValueError):
    """An archive or record that breaks the format."""


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMES, f'page:{page_id}')}>"


def _field(text: str) -> str:
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", text)


def make_record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """A response record, or a revisit of ``refers_to`` that keeps the HTTP header alone."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    head = {
        "WARC-Type": "response" if refers_to is None else "revisit",
        "WARC-Record-ID": record_id(page_id),
        "WARC-Date": DATE,
        "WARC-Target-URI": _field(url) if url else f"urn:page:{page_id}",
        "WARC-Payload-Digest": f"sha1:{digest}",
        "Content-Type": "application/http;msgtype=response",
        "X-Page-Id": str(page_id),
    }
    if refers_to is not None:
        head["WARC-Refers-To"] = record_id(refers_to)
        head["WARC-Profile"] = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
        head["X-Refers-To-Page-Id"] = str(refers_to)
    block = http if refers_to is not None else http + payload
    head["Content-Length"] = str(len(block))
    lines = "".join(f"{k}: {v}\r\n" for k, v in head.items())
    return f"WARC/1.1\r\n{lines}\r\n".encode() + block + _END


def parse_record(raw: bytes) -> dict:
    """Checks a record and returns its page_id, url, type, digest, payload length and bytes."""
    top, gap, rest = raw.partition(_END)
    lines = top.decode("utf-8").split("\r\n")
    if not gap or lines[0] not in ("WARC/1.0", "WARC/1.1"):
        raise BadArchive("no version line")
    head = {}
    for line in lines[1:]:
        name, colon, value = line.partition(":")
        if not colon or not name.strip():
            raise BadArchive(f"bad header line {line[:40]!r}")
        head[name.strip().lower()] = value.strip()
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in head:
            raise BadArchive(f"{name} is missing")
    if not head["content-length"].isdigit() or len(rest) != int(head["content-length"]) + len(_END) or not rest.endswith(_END):
        raise BadArchive("Content-Length differs from the block")
    http, gap, payload = rest[: -len(_END)].partition(_END)
    length = re.search(rb"(?im)^content-length: *(\d+)\r?$", http)
    if not gap or not length:
        raise BadArchive("no HTTP header in the block")
    digest = head.get("warc-payload-digest", "").removeprefix("sha1:")
    kind = head["warc-type"]
    if kind == "response":
        if len(payload) != int(length[1]):
            raise BadArchive("the payload has another length than its header says")
        if base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
            raise BadArchive("the payload has another digest than its header says")
    elif kind != "revisit" or payload or "warc-refers-to" not in head:
        raise BadArchive("neither a response nor a revisit")
    number = lambda k: None if head.get(k, "None") == "None" else int(head[k])
    return {"page_id": number("x-page-id"), "url": head.get("warc-target-uri"), "payload_bytes": int(length[1]), "payload_digest": digest, "record_type": kind, "refers_to": number("x-refers-to-page-id"), "payload": payload}


def train(samples: list[bytes]) -> zstandard.ZstdCompressionDict:
    """A dictionary from sample payloads; raw content of the first ones where training can't work."""
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples, k=256, d=8)
    except zstandard.ZstdError:
        return zstandard.ZstdCompressionDict(b"".join(samples)[:DICTIONARY_BYTES] or b"<!DOCTYPE html>", dict_type=zstandard.DICT_TYPE_RAWCONTENT)


def dictionary_frame(words: zstandard.ZstdCompressionDict) -> bytes:
    raw = zstandard.ZstdCompressor(level=9).compress(words.as_bytes())
    return SKIPPABLE.to_bytes(4, "little") + len(raw).to_bytes(4, "little") + raw


def frame_length(raw: memoryview, at: int) -> int:
    """Bytes of the frame that begins at ``at``, by its block headers."""
    try:
        params = zstandard.get_frame_parameters(raw[at : at + 18])
        end = at + zstandard.frame_header_size(raw[at : at + 18])
    except zstandard.ZstdError as why:
        raise BadArchive(f"no frame at {at}") from why
    while True:
        if end + 3 > len(raw):
            raise BadArchive("the archive ends inside a frame")
        block = int.from_bytes(raw[end : end + 3], "little")
        end += 3 + (1 if block >> 1 & 3 == 1 else block >> 3)
        if block & 1:
            break
    end += 4 if params.has_checksum else 0
    if end > len(raw):
        raise BadArchive("the archive ends inside a frame")
    return end - at


def read_archive(raw: bytes):
    """The checked records of an archive, in order."""
    view = memoryview(raw)
    at, words = 0, None
    if len(raw) >= 8 and int.from_bytes(raw[:4], "little") == SKIPPABLE:
        at = 8 + int.from_bytes(raw[4:8], "little")
        held = raw[8:at]
        if len(held) != at - 8:
            raise BadArchive("the archive ends inside its dictionary")
        if held[:4] == b"\x28\xb5\x2f\xfd":
            held = zstandard.ZstdDecompressor().decompress(held, max_output_size=1 << 26)
        words = zstandard.ZstdCompressionDict(held)
    opener = zstandard.ZstdDecompressor(dict_data=words) if words else zstandard.ZstdDecompressor()
    while at < len(raw):
        n = frame_length(view, at)
        if 0x184D2A50 <= int.from_bytes(raw[at : at + 4], "little") <= 0x184D2A5F:
            raise BadArchive("a skippable frame after the first")
        try:
            record = opener.decompress(view[at : at + n])
        except zstandard.ZstdError as why:
            raise BadArchive(f"the frame at {at} can't be decoded") from why
        yield parse_record(record)
        at += n


def assign(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """page_id, url, html with the payload's SHA-1 and, for a revisit, the page that it repeats."""
    rows = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html")).withColumn("sha", F.sha1(F.encode("html", "UTF-8"))).withColumn("n", F.octet_length("html"))
    best = rows.where(F.col("n") >= min_bytes).groupBy("sha", "n").agg(F.max("page_id").alias("top"))
    rows = rows.join(best, ["sha", "n"], "left")
    repeat = F.col("top").isNotNull() & (F.col("page_id").isNull() | (F.col("page_id") < F.col("top")))
    return rows.select("page_id", "url", "html", "sha", F.when(repeat, F.col("top")).alias("top"))


def write_archives(pages: DataFrame, work: Workspace, min_bytes: int = 0) -> DataFrame:
    """Writes all pages; returns the manifest (uri, n_records)."""
    folder, limit = work.at("archives"), ARCHIVE_BYTES
    schema = pa.schema([("uri", pa.string()), ("n_records", pa.int64())])

    def write(batches):
        first, sample, parts, state = [], 0, [], {"n": 0, "bytes": 0, "press": None}

        def begin():
            words = train([x["html"].encode() for x in first])
            state["press"] = zstandard.ZstdCompressor(level=3, dict_data=words, write_checksum=True)
            parts.append(dictionary_frame(words))

        def add(row):
            payload = row["html"].encode()
            digest = base64.b32encode(bytes.fromhex(row["sha"])).decode()
            parts.append(state["press"].compress(make_record(row["page_id"], row["url"], payload, digest, row["top"])))
            state["n"] += 1
            state["bytes"] += len(payload)

        def end():
            out = pa.RecordBatch.from_pydict({"uri": [files.put(folder, b"".join(parts), ".warc.zst")], "n_records": [state["n"]]}, schema=schema)
            parts.clear()
            state.update(n=0, bytes=0, press=None)
            return out

        for batch in batches:
            for row in (r for i in range(0, batch.num_rows, 64) for r in batch.slice(i, 64).to_pylist()):
                if state["press"]:
                    add(row)
                else:
                    first.append(row)
                    sample += len(row["html"])
                    if sample >= SAMPLE_BYTES:
                        begin()
                        for x in first:
                            add(x)
                        first, sample = [], 0
                if state["bytes"] >= limit:
                    yield end()
        if first:
            begin()
            for x in first:
                add(x)
        if state["n"]:
            yield end()

    return work.save(assign(pages, min_bytes).mapInArrow(write, "uri string, n_records long"), "manifest")


def read_archives(manifest: DataFrame, payloads: bool = False) -> DataFrame:
    """The records of all archives of a manifest."""
    schema = [("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())] + [("payload", pa.binary())] * payloads

    def read(batches):
        for batch in batches:
            for row in batch.to_pylist():
                held, count, size = [], 0, 0
                for record in read_archive(files.get(row["uri"])):
                    held.append({k: record[k] for k, _ in schema})
                    count += 1
                    size += len(record["payload"]) * payloads
                    if len(held) >= 4096 or size > 1 << 24:
                        yield pa.RecordBatch.from_pylist(held, schema=pa.schema(schema))
                        held, size = [], 0
                if count != row["n_records"]:
                    raise BadArchive(f"{row['uri']} has {count} records, not {row['n_records']}")
                if held:
                    yield pa.RecordBatch.from_pylist(held, schema=pa.schema(schema))

    n = max(1, manifest.count())
    return manifest.repartition(min(n, 100_000), "uri").mapInArrow(read, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long" + (", payload binary" if payloads else ""))


def archive_report(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Writes the archives and reads them back: a row per page."""
    work = Workspace(pages.sparkSession, "warc")
    return read_archives(write_archives(pages, work, min_bytes)).drop("url")


#: DuckDB for the columns of ``archive_report``; the digest's base32 is built from its hex digits.
ORACLE = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS payload FROM pages),
h AS (SELECT page_id, octet_length(payload) AS payload_bytes, sha1(payload) AS sha FROM p),
b AS (SELECT *, list_reduce(list_transform(string_split(upper(sha), ''), lambda c: CASE c WHEN '0' THEN '0000' WHEN '1' THEN '0001' WHEN '2' THEN '0010' WHEN '3' THEN '0011' WHEN '4' THEN '0100' WHEN '5' THEN '0101' WHEN '6' THEN '0110' WHEN '7' THEN '0111' WHEN '8' THEN '1000' WHEN '9' THEN '1001' WHEN 'A' THEN '1010' WHEN 'B' THEN '1011' WHEN 'C' THEN '1100' WHEN 'D' THEN '1101' WHEN 'E' THEN '1110' ELSE '1111' END), lambda x, y: x || y) AS bits,
             max(page_id) OVER (PARTITION BY sha, payload_bytes) AS top FROM h)
SELECT page_id, payload_bytes::BIGINT AS payload_bytes,
       array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + 16 * substr(bits, 1 + 5 * i, 1)::INT + 8 * substr(bits, 2 + 5 * i, 1)::INT + 4 * substr(bits, 3 + 5 * i, 1)::INT + 2 * substr(bits, 4 + 5 * i, 1)::INT + substr(bits, 5 + 5 * i, 1)::INT, 1)), '') AS payload_digest,
       CASE WHEN top IS NOT NULL AND (page_id IS NULL OR page_id < top) THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN top IS NOT NULL AND (page_id IS NULL OR page_id < top) THEN top END AS refers_to FROM b
"""
