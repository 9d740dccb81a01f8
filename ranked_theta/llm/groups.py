"""Groups of consecutive rows in a stream of sorted Arrow batches."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa


def runs(batches: Iterable[pa.RecordBatch], keys: int) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of whole groups with the bounds of the groups in them.

    The first ``keys`` columns are 64-bit integers without nulls, and rows with equal
    keys follow each other. The last group of a batch waits for the next batch, so that
    memory holds a batch and one group.
    """
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        change = _changes(batch, keys)
        joins = bool(held) and all(held[-1].column(k)[held[-1].num_rows - 1].as_py() == batch.column(k)[0].as_py() for k in range(keys))
        cut = int(change[-1]) if len(change) else 0
        if not cut and (joins or not held):
            held.append(batch)
            continue
        done = held + ([batch.slice(0, cut)] if cut else [])
        held = [batch.slice(cut)]
        yield _with_bounds(done, keys)
    if held:
        yield _with_bounds(held, keys)


def _changes(batch, keys: int) -> np.ndarray:
    """Rows that begin a group, the first row left out."""
    new = np.zeros(max(0, batch.num_rows - 1), bool)
    for k in range(keys):
        column = batch.column(k).to_numpy(zero_copy_only=False) if isinstance(batch, pa.RecordBatch) else batch.column(k).to_numpy()
        new |= column[1:] != column[:-1]
    return np.flatnonzero(new) + 1


def _with_bounds(parts: list[pa.RecordBatch], keys: int) -> tuple[pa.Table, np.ndarray]:
    table = pa.Table.from_batches(parts).combine_chunks()
    return table, np.concatenate([[0], _changes(table, keys), [table.num_rows]])
