"""Secret scans with structural confirmation.

Base kinds, leftmost and non-overlapping per kind: ``assign`` (a credential word, a sign
and a value of six characters or more), ``access`` (AKIA and capitals or digits, 20 or
more in all) and ``hex`` (24 or more lower-case hex digits). Further kinds are reported
only when their structure holds: ``pem`` (armoured key whose body decodes to nested DER
or key lengths), ``jwt`` (three parts; the first decodes to a JSON object with "alg", the
second to a JSON object), ``der`` (base64 or hex run that decodes to a DER sequence whose
nested lengths fill it exactly), ``ssh`` (base64 run that decodes to a key name and
length-prefixed fields that fill it exactly).

A text is scanned by patterns only if it has a run of 17 or more token characters, a
credential word or the head of an armoured key; all are found on the bytes of a whole
batch. The shortest ``jwt`` has 17 token characters in a row (12 for an object with "alg",
3 for an empty one, two dots), a ``pem`` has its head, and the other kinds need longer
runs or a credential word, so no span is missed. Offsets are code points, end exclusive.

Nulls: a null text is empty; null ids stay null. Repeated rows give equal rows. Empty
table: empty result.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import textkit
from .workspace import importable

# The base patterns and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24
KINDS = ("assign", "access", "hex", "pem", "jwt", "der", "ssh")

WORDS = re.compile(rb"passw|secret|token|api_?key|-----BEGIN ", re.IGNORECASE)
#: Token characters in a row that any kind needs, unless it has one of the words.
RUN_LEAST = 17
_PEM = re.compile(r"-----BEGIN ([A-Z0-9 ]+)-----([A-Za-z0-9+/=\s]+)-----END \1-----")
_JWT = re.compile(r"(?<![A-Za-z0-9_-])([A-Za-z0-9_-]{8,})\.([A-Za-z0-9_-]{2,})\.([A-Za-z0-9_-]*)")
_B64 = re.compile(r"(?<![A-Za-z0-9+/])[A-Za-z0-9+/]{32,}={0,2}")
_RUN = np.zeros(256, bool)
_RUN[[ord(c) for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-"]] = True


def der_fills(raw: bytes, depth: int = 0) -> bool:
    """Whether ``raw`` is one DER element after another, nested lengths included, to its end."""
    at = 0
    while at < len(raw):
        if at + 2 > len(raw):
            return False
        tag, n = raw[at], raw[at + 1]
        at += 2
        if n & 0x80:
            k = n & 0x7F
            if not 1 <= k <= 4 or at + k > len(raw):
                return False
            n = int.from_bytes(raw[at : at + k], "big")
            at += k
            if n < 0x80 or n < 1 << 8 * (k - 1):
                return False
        if at + n > len(raw) or tag & 0x1F == 0x1F:
            return False
        if tag & 0x20 and (depth > 16 or not der_fills(raw[at : at + n], depth + 1)):
            return False
        at += n
    return True


def der_key(raw: bytes) -> bool:
    """A sequence of 16 bytes or more that fills ``raw`` and holds two elements at least."""
    if len(raw) < 16 or raw[0] != 0x30:
        return False
    head = 2 + (raw[1] & 0x7F if raw[1] & 0x80 else 0)
    inner = raw[head:]
    return der_fills(raw) and len(inner) > 3 and inner[0] in (0x02, 0x03, 0x04, 0x06, 0x30, 0x31)


def ssh_key(raw: bytes) -> bool:
    """Length-prefixed fields to the end, the first of which names a key type; or the private key magic."""
    if raw.startswith(b"openssh-key-v1\0"):
        return True
    at, fields = 0, []
    while at < len(raw):
        n = int.from_bytes(raw[at : at + 4], "big")
        if at + 4 + n > len(raw) or len(fields) > 16:
            return False
        fields.append(raw[at + 4 : at + 4 + n])
        at += 4 + n
    return len(fields) >= 2 and re.fullmatch(rb"(ssh|ecdsa|sk)-[a-z0-9@.-]+", fields[0]) is not None


def unbase64(text: str, url: bool = False) -> bytes | None:
    body = text.rstrip("=")
    if len(body) % 4 == 1:
        return None
    if url:
        body = body.replace("-", "+").replace("_", "/")
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _json_object(raw: bytes | None) -> dict | None:
    try:
        found = json.loads(raw.decode("utf-8")) if raw else None
    except (ValueError, RecursionError):
        return None
    return found if isinstance(found, dict) else None


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_LEAST]
    out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
    return out + [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]


def confirmed_spans(text: str) -> list[tuple[int, int, str]]:
    """Candidates whose decoded structure holds."""
    out, armoured = [], []
    for m in _PEM.finditer(text):
        raw = unbase64(re.sub(r"\s", "", m[2]))
        if raw and (der_key(raw) or ssh_key(raw)):
            out.append((m.start(), m.end(), "pem"))
            armoured.append(m.span())
    at = 0
    while m := _JWT.search(text, at):
        head = _json_object(unbase64(m[1], True))
        if head is not None and "alg" in head and _json_object(unbase64(m[2], True)) is not None:
            out.append((m.start(), m.end(), "jwt"))
            at = m.end()
        else:  # a token can begin at the next part
            at = m.start(2)
    for m in _B64.finditer(text):
        if any(a <= m.start() < b for a, b in armoured):
            continue
        raw = unbase64(m[0])
        digits = m[0] if len(m[0]) % 2 == 0 and re.fullmatch(r"[0-9a-fA-F]+", m[0]) else None
        if raw and ssh_key(raw):
            out.append((m.start(), m.end(), "ssh"))
        elif raw and der_key(raw) or digits and der_key(bytes.fromhex(digits)):
            out.append((m.start(), m.end(), "der"))
    return out


def joined(spans: list[tuple[int, int, str]]) -> str:
    order = sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))
    return ",".join(f"{k}:{a}:{b}" for a, b, k in order)


def suspects(column: pa.Array) -> np.ndarray:
    """Which texts have a run of ``RUN_LEAST`` or more token characters, or one of the words."""
    data, off = textkit.utf8(column)
    found = np.zeros(len(column), bool)
    n = len(data)
    for a in range(0, n, 1 << 20):
        b = min(n, a + (1 << 20) + HEX_LEAST)  # parts overlap by more than a run
        gaps = np.concatenate([[-1], np.flatnonzero(~_RUN[data[a:b]]), [b - a]])
        ends = gaps[1:][np.diff(gaps) > RUN_LEAST]
        found[np.minimum(np.searchsorted(off, ends - 1 + a, "right") - 1, len(column) - 1)] = True
        # a run over the border of two texts marks both
        starts = gaps[:-1][np.diff(gaps) > RUN_LEAST] + 1 + a
        first = np.searchsorted(off, starts, "right") - 1
        last = np.searchsorted(off, ends - 1 + a, "right") - 1
        for i, j in zip(first[first < last], last[first < last], strict=True):
            found[max(0, i) : j + 1] = True
    raw = data.tobytes()
    for m in WORDS.finditer(raw):
        found[np.searchsorted(off, m.start(), "right") - 1] = True
    return found


def scan(docs: DataFrame, matches: bool = False) -> DataFrame:
    """doc_id, counts of the base kinds, their digest, and all spans; with ``matches`` the matched strings too."""
    schema = [("doc_id", pa.int64()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_sha256", pa.string()), ("spans", pa.string())] + [("matches", pa.list_(pa.string()))] * matches
    importable(docs.sparkSession)
    nothing = hashlib.sha256(b"").hexdigest()

    def find(batches):
        for batch in batches:
            ids, at = batch.column(0), 0
            for part in textkit.slices(batch.column(1)):
                n = len(part)
                counts = np.zeros((3, n), np.int64)
                digest, spans, texts = [nothing] * n, [""] * n, [[] for _ in range(n)]
                for i in np.flatnonzero(suspects(part)):
                    text = part[int(i)].as_py() or ""
                    base = base_spans(text)
                    every = base + confirmed_spans(text)
                    for k in range(3):
                        counts[k, i] = sum(s[2] == KINDS[k] for s in base)
                    digest[i], spans[i] = hashlib.sha256(joined(base).encode()).hexdigest(), joined(every)
                    texts[i] = [text[a:b] for a, b, _ in sorted(every)]
                columns = [ids.slice(at, n), *[pa.array(c) for c in counts], pa.array(digest), pa.array(spans)] + [pa.array(texts, pa.list_(pa.string()))] * matches
                yield pa.RecordBatch.from_arrays(columns, schema=pa.schema(schema))
                at += n

    return docs.select("doc_id", "text").mapInArrow(find, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string" + (", matches array<string>" if matches else ""))
