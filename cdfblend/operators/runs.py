"""Streaming over sorted Arrow batches: one fold per run of equal keys, without holding a group."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def boundaries(batch: pa.RecordBatch, n_keys: int) -> np.ndarray:
    """Row indexes at which any of the first ``n_keys`` columns changes (nulls equal each other)."""
    changed = np.zeros(max(batch.num_rows - 1, 0), dtype=bool)
    for k in range(n_keys):
        col = batch.column(k)
        a, b = col.slice(0, len(col) - 1), col.slice(1)
        if pa.types.is_nested(col.type):
            changed |= np.array([x != y for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], dtype=bool)
            continue
        differ = pc.fill_null(pc.not_equal(a, b), False)
        null = pc.not_equal(pc.is_null(a), pc.is_null(b))
        changed |= np.asarray(pc.or_(differ, null))
    return np.flatnonzero(changed) + 1


def fold_runs(batches: Iterator[pa.RecordBatch], n_keys: int, start: Callable[[], object], add: Callable[[object, pa.RecordBatch], None], finish: Callable[[tuple, object], dict | list[dict] | None], schema: pa.Schema, short: int = 0, bulk: Callable[[pa.RecordBatch, np.ndarray, np.ndarray], pa.RecordBatch] | None = None) -> Iterator[pa.RecordBatch]:
    """``add`` gets slices of one key in order; ``finish`` turns a closed run into a row, rows or None.

    Runs of fewer than ``short`` rows that lie inside a batch go to ``bulk`` together: (batch, their starts, their ends).
    """
    key: tuple | None = None
    state: object = None

    def close() -> list[dict]:
        got = finish(key, state) if state is not None else None
        return got if isinstance(got, list) else [got] if got is not None else []

    for b in batches:
        if not b.num_rows:
            continue
        lo = np.concatenate([[0], boundaries(b, n_keys)])
        hi = np.concatenate([lo[1:], [b.num_rows]])
        if bulk is not None:
            inner = hi - lo < short
            inner[[0, -1]] = False
            if inner.any():
                yield bulk(b, lo[inner], hi[inner])
                lo, hi = lo[~inner], hi[~inner]
        out: list[dict] = []
        for i, j in zip(lo.tolist(), hi.tolist(), strict=True):
            here = tuple(b.column(k)[i].as_py() for k in range(n_keys))
            if here != key or state is None:
                out += close()
                key, state = here, start()
            add(state, b.slice(i, j - i))
        if out:
            yield pa.RecordBatch.from_pylist(out, schema=schema)
    rows = close()
    if rows:
        yield pa.RecordBatch.from_pylist(rows, schema=schema)
