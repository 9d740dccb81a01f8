"""Vectorised text primitives over Arrow string columns.

Words are maximal runs of bytes other than space and the five ASCII controls 9-13;
A-Z count as a-z. Hashes are computed on the UTF-8 bytes, a block at a time, so that
memory stays bounded for a text of any length.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Words of a shingle.
SHINGLE = 5
#: Bytes hashed at once.
BLOCK = 1 << 17
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_U = np.uint64


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: two multiply-xorshift rounds, in a new array."""
    h = h ^ (h >> _U(33))
    h *= _U(0xFF51AFD7ED558CCD)
    h ^= h >> _U(33)
    h *= _U(0xC4CEB9FE1A85EC53)
    h ^= h >> _U(33)
    return h


_TABLE = mix(np.arange(1, 257, dtype=np.uint64) * _U(0x9E3779B97F4A7C15))
_BASE = 0x2545F4914F6CDD1D
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the hash base and of its inverse modulo 2**64."""
    if len(_powers.get("p", ())) < n:
        for key, base in (("p", _BASE), ("q", pow(_BASE, -1, 1 << 64))):
            x = np.full(n, base, np.uint64)
            x[0] = 1
            _powers[key] = np.multiply.accumulate(x)
    return _powers["p"][:n], _powers["q"][:n]


def prefix_hash(codes: np.ndarray) -> np.ndarray:
    """S with S[j]-S[i] = sum of codes[k] * base**k over i <= k < j."""
    out = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum(codes * powers(len(codes))[0], out=out[1:])
    return out


_remembered: dict[str, dict] = {}


def remembered(name: str) -> dict:
    """A dictionary that a worker keeps between tasks, until it works on something else (``frugal``)."""
    return _remembered.setdefault(name, {})


def forget(but: str | None) -> None:
    for name, kept in _remembered.items():
        if name != but:
            kept.clear()


def give_back() -> None:
    """Memory that the allocators hold on to goes back to the system."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # another C library
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def frugal(work, own: str | None = None):
    """``work`` on batches, for a worker that many tasks share in turn: what other operators remember there is dropped first."""

    def run(batches):
        forget(own)
        yield from work(batches)
        give_back()

    return run


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, off, data = column.buffers()
    if not len(column) or off is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(off, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.zeros(0, np.uint8) if data is None else np.frombuffer(data, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def _blocks(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int]]:
    """Cuts that fall between words: at a text's start or after white space."""
    at, n = 0, len(data)
    while at < n:
        end = min(at + BLOCK, n)
        if end < n:
            cut = int(offsets[np.searchsorted(offsets, end, "right") - 1])
            if cut <= at:
                gaps = np.flatnonzero(_SPACE[data[at:end]])
                cut = at + int(gaps[-1]) + 1 if len(gaps) else 0
            if cut <= at:  # one word longer than a block
                stop = int(offsets[np.searchsorted(offsets, end, "left")])
                cut = next((i + int(g[0]) + 1 for i in range(end, stop, BLOCK) if len(g := np.flatnonzero(_SPACE[data[i : min(i + BLOCK, stop)]]))), stop)
            end = cut
        yield at, end
        at = end


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word of every text, and the number of words before each text."""
    (found,), bounds = words_by(data, offsets, _FOLD)
    return found, bounds


def words_by(data: np.ndarray, offsets: np.ndarray, *folds: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """As ``words``, with a hash for each map of bytes in ``folds``."""
    hashes, starts = [[] for _ in folds], []
    for a, b in _blocks(data, offsets):
        part = data[a:b]
        solid = ~_SPACE[part]
        first, last = solid.copy(), solid.copy()
        first[1:] &= ~solid[:-1]
        last[:-1] &= ~solid[1:]
        edges = offsets[(offsets > a) & (offsets < b)] - a
        first[edges] = solid[edges]
        last[edges - 1] = solid[edges - 1]
        s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
        back = powers(len(part) + 1)[1][s]
        for out, fold in zip(hashes, folds, strict=True):
            acc = prefix_hash(_TABLE[fold][part])
            out.append(mix((acc[e] - acc[s]) * back))
        starts.append(s + a)
    if not starts:
        return [np.zeros(0, np.uint64) for _ in folds], np.zeros(len(offsets), np.int64)
    return [np.concatenate(out) for out in hashes], np.searchsorted(np.concatenate(starts), offsets)


_STEP = [pow(_BASE, k + 3, 1 << 64) | 1 for k in range(SHINGLE)]


def shingles(word: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every run of five words, and the number of runs before each text.

    A text of one to four words gives its whole sequence as one; one without words none.
    """
    n = np.diff(bounds)
    count = np.where(n >= SHINGLE, n - SHINGLE + 1, np.minimum(n, 1))
    out_bounds = np.concatenate([[0], np.cumsum(count)])
    out = np.zeros(int(out_bounds[-1]), np.uint64)
    if len(word) >= SHINGLE:
        m = len(word) - SHINGLE + 1
        acc = word[:m] * _U(_STEP[0])
        for k in range(1, SHINGLE):
            acc += word[k : k + m] * _U(_STEP[k])
        acc = mix(acc)
        full = np.flatnonzero(n >= SHINGLE)
        take = np.zeros(len(word) + 1, np.int64)
        np.add.at(take, bounds[full], 1)
        np.add.at(take, bounds[full] + count[full], -1)
        target = np.zeros(len(out) + 1, np.int64)
        np.add.at(target, out_bounds[full], 1)
        np.add.at(target, out_bounds[full + 1], -1)
        out[np.cumsum(target)[:-1] > 0] = acc[np.cumsum(take)[:m] > 0]
    for d in np.flatnonzero((n > 0) & (n < SHINGLE)):
        seq = word[bounds[d] : bounds[d + 1]]
        total = sum(int(h) * _STEP[k] for k, h in enumerate(seq)) + len(seq)
        out[out_bounds[d]] = mix(np.array([total & (2**64 - 1)], np.uint64))[0]
    return out, out_bounds


def distinct(h: np.ndarray) -> np.ndarray:
    """Sorted distinct values."""
    h = np.sort(h)
    return h[np.concatenate([[True], h[1:] != h[:-1]])] if len(h) else h


def shingle_sets(column: pa.Array) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    for part in slices(column):
        sh, b = shingles(*words(*utf8(part)))
        for i in range(len(part)):
            yield distinct(sh[b[i] : b[i + 1]])


def slices(column: pa.Array, most: int = 32 * BLOCK) -> Iterator[pa.Array]:
    """Consecutive parts of a column of about ``most`` bytes, one text at least."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, off = utf8(column)
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield column.slice(i, j - i)
        i = j


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def row_key() -> Column:
    """What a row's text is found by, as ``row``: its id, or a hash of the text where there is none."""
    return F.coalesce("doc_id", F.xxhash64("text")).alias("row")


def by_row(docs: DataFrame) -> DataFrame:
    """(row, text); equal texts without id have one row key, and one of them will do."""
    return docs.where("doc_id is not null").select(row_key(), "text").unionByName(docs.where("doc_id is null").select(row_key(), "text").distinct())
