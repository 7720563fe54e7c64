"""Giving memory back: Python workers live on after a task, and what they keep counts against their executor."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

try:
    _trim = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError):  # no glibc
    _trim = None


def give_back() -> None:
    """Return freed pages of Arrow's pool and of the C allocator to the system."""
    gc.collect(0)
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A task function for ``mapInArrow`` that gives memory back when its task ends, however it ends."""

    @wraps(run)
    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def row_ranges(col: pa.Array, limit: int) -> Iterator[tuple[int, int]]:
    """Row ranges ``[i, j)`` of a string column of at most ``limit`` bytes each; a longer row stands alone."""
    ends = np.cumsum(np.asarray(pc.fill_null(pc.binary_length(col), 0)), dtype=np.int64)
    i, before = 0, 0
    while i < len(ends):
        j = max(i + 1, int(np.searchsorted(ends, before + limit, side="right")))
        yield i, j
        i, before = j, int(ends[j - 1])
