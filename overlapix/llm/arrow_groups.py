"""Whole groups out of sorted Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def column(array: pa.Array) -> np.ndarray:
    """Numbers as they are; binary values as rows of bytes, shorter ones filled with zeros."""
    if pa.types.is_binary(array.type) or pa.types.is_large_binary(array.type):
        if not len(array):
            return np.zeros((0, 0), np.uint8)
        values = array.to_pylist()
        width = max(map(len, values))
        return np.frombuffer(b"".join(v.ljust(width, b"\0") for v in values), np.uint8).reshape(len(values), width)
    return array.to_numpy(zero_copy_only=False)


def whole_groups(batches: Iterator[pa.RecordBatch], keys: int = 1, rows: int = 20_000) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """``(columns, starts)`` of complete groups from batches sorted by their first ``keys`` columns.

    About ``rows`` rows come at a time, more where one group is larger.
    """
    held: list[pa.RecordBatch] = []
    count = 0

    def starts_of(table: pa.Table) -> np.ndarray:
        change = np.zeros(max(0, table.num_rows - 1), bool)
        for i in range(keys):
            c = table.column(i).to_numpy()
            change |= c[1:] != c[:-1]
        return np.concatenate([[0], np.flatnonzero(change) + 1]) if table.num_rows else np.array([], int)

    def arrays(table: pa.Table) -> list[np.ndarray]:
        return [column(c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c) for c in table.columns]

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        count += batch.num_rows
        if count < rows:
            continue
        table = pa.Table.from_batches(held)
        starts = starts_of(table)
        cut = int(starts[-1])
        if cut:
            yield arrays(table.slice(0, cut)), starts[:-1]
            rest = table.slice(cut)
            held, count = rest.to_batches(), rest.num_rows
    if held:
        table = pa.Table.from_batches(held)
        yield arrays(table), starts_of(table)
