"""Byte-level helpers over Arrow string columns, shared by the text operators."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

#: The bytes that separate words (space, tab to carriage return).
SPACE_BYTES = bytes([0x20, *range(0x09, 0x0E)])

IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[list(SPACE_BYTES)] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def utf8_view(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column without copying; null rows are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    if n == 0 or data is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    ends = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)
    return np.frombuffer(data, dtype=np.uint8), ends[column.offset : column.offset + n + 1].astype(np.int64)


def byte_chunks(offsets: np.ndarray, limit: int) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer row is a range of its own."""
    n, at = len(offsets) - 1, 0
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        to = min(n, max(to, at + 1))
        yield at, to
        at = to


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of non-space bytes."""
    ink = np.empty(len(data) + 2, dtype=np.int8)
    ink[0] = ink[-1] = 0
    ink[1:-1] = ~IS_SPACE[data]
    turns = np.diff(ink)
    return np.flatnonzero(turns == 1), np.flatnonzero(turns == -1)


def lowered(data: np.ndarray) -> np.ndarray:
    """ASCII lower case; other bytes stay."""
    return LOWER[data]


def give_back() -> None:
    """Return freed memory to the system: workers serve many tasks, and allocators keep it."""
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


def tidy(run: Callable) -> Callable:
    """A mapInArrow function that gives memory back at the end of its partition."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped
