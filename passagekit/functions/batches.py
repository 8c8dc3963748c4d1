"""Arrow batches of sorted rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def whole(batches: Iterator[pa.RecordBatch], *keys: str) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of whole groups and the places where their groups end (from 0), of batches sorted by keys (integers). Held are one batch and one group."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        first = starts(pa.Table.from_batches([batch]), keys)
        if held and len(starts(pa.concat_tables([held[-1].slice(held[-1].num_rows - 1), pa.Table.from_batches([batch.slice(0, 1)])]), keys)) > 1:
            yield pa.concat_tables(held).combine_chunks(), np.array([0, size])
            held, size = [], 0
        t = pa.Table.from_batches([batch])
        if len(first) > 1:
            t = pa.concat_tables([*held, t.slice(0, first[-1])]).combine_chunks()
            yield t, np.append(0, first[1:] + size)
            held, size = [], 0
            t = pa.Table.from_batches([batch]).slice(first[-1])
        held, size = [*held, t], size + t.num_rows
    if held:
        yield pa.concat_tables(held).combine_chunks(), np.array([0, size])


def starts(t: pa.Table, keys: tuple) -> np.ndarray:
    """Where groups begin; nulls are a group."""
    cols = [t.column(k).combine_chunks() for k in keys]
    every = [v for c in cols for v in (c.is_null().to_numpy(zero_copy_only=False), c.fill_null(0).to_numpy())]
    return np.flatnonzero(np.concatenate([[True], np.any([v[1:] != v[:-1] for v in every], 0)]))
