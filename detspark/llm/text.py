"""Vectorised tokenising and hashing of Arrow text columns.

A column is handled as one byte buffer.  Words are found by class changes between neighbouring bytes and hashed
through a prefix polynomial, so no Python object is made per word.  Buffers are taken in chunks of about ``CHUNK``
bytes, which bounds the temporaries whatever the batch or document length is.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CHUNK = 1 << 18
_BASE = 0x9E3779B97F4A7C15
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: tuple[np.ndarray, np.ndarray] | None = None

#: byte classes: 0 white space, 1 letters, digits and non-ASCII bytes, 2 other printable bytes
CLASSES = np.full(256, 2, np.uint8)
CLASSES[[9, 10, 11, 12, 13, 32]] = 0
for _low, _high in ((48, 58), (65, 91), (97, 123), (128, 256)):
    CLASSES[_low:_high] = 1
#: white space against everything else
BLANKS = (CLASSES > 0).astype(np.uint8)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


#: frees what operators keep in a Python worker between tasks; a worker serves the tasks of all operators in turn
HELD: list = []


#: holds the columns of a table that an operator doesn't use, so that their names can't clash with its own
REST = "_rest"


def carried_rest(docs: DataFrame, used: tuple[str, ...]) -> Column:
    """All columns of ``docs`` but the ``used`` ones, as one named ``REST``."""
    others = [F.col(f"`{c}`") for c in docs.columns if c not in used]
    return (F.struct(*others) if others else F.lit(0)).alias(REST)


def carried(docs: DataFrame, *used: str) -> DataFrame:
    """``docs`` as its ``used`` columns and ``REST``."""
    return docs.select(*used, carried_rest(docs, used))


def unpacked(docs: DataFrame, changed: dict[str, Column], used: tuple[str, ...]) -> list[Column]:
    """The columns of ``docs`` again, in their order, from rows that ``carried`` them; ``changed`` gives new values."""
    return [(changed[c] if c in changed else F.col(c) if c in used else F.col(REST)[c]).cast(docs.schema[c].dataType).alias(c) for c in docs.columns]


def tidy() -> None:
    """Give back freed memory that allocators of this worker hold on to."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def release() -> None:
    """Give back what earlier tasks of this worker kept."""
    for free in HELD:
        free()
    tidy()


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if _powers is None or len(_powers[0]) < n:
        n = max(n, CHUNK + 1024)
        with np.errstate(over="ignore"):
            _powers = tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full(n - 1, np.uint64(b))]), dtype=np.uint64) for b in (_BASE, _BASE_INVERSE))
    return _powers


def mix(h: np.ndarray) -> np.ndarray:
    """Finalise 64-bit hashes so that every output bit depends on every input bit."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return h ^ (h >> np.uint64(33))


def column_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a string or binary column; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    if not len(column):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    return offsets, np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)


def pieces(offsets: np.ndarray, data: np.ndarray, separators: np.ndarray, size: int | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Cut a column into chunks: yields (rows, bounds, bytes), where piece k of the chunk belongs to ``rows[k]`` and spans ``bounds[k:k+2]``.

    Short texts are taken together.  A text longer than ``size`` is cut after a separator byte, so that no word is split.
    """
    size = size or CHUNK
    rows, bounds, start = [], [], 0
    for row in range(len(offsets) - 1):
        low, high = int(offsets[row]), int(offsets[row + 1])
        while True:
            if not rows:
                start = low
            end = high
            if high - low > size:
                found = np.flatnonzero(separators[data[low : low + size]])
                if len(found):
                    end = low + int(found[-1]) + 1
                else:  # one unbroken run: take it to its end
                    rest = np.flatnonzero(separators[data[low + size : high]])
                    end = low + size + int(rest[0]) + 1 if len(rest) else high
            rows.append(row)
            bounds.append(low - start)
            if end - start >= size or end < high:
                yield np.array(rows), np.array([*bounds, end - start]), data[start:end]
                rows, bounds = [], []
            low = end
            if low >= high:
                break
    if rows:
        yield np.array(rows), np.array([*bounds, int(offsets[-1]) - start]), data[start : int(offsets[-1])]


def spans(data: np.ndarray, classes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of one non-zero class that do not cross a bound."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = classes[data]
    change = np.empty(len(data) + 1, bool)
    change[0] = change[-1] = True
    np.not_equal(kind[1:], kind[:-1], out=change[1:-1])
    change[bounds] = True
    edges = np.flatnonzero(change)
    keep = kind[edges[:-1]] > 0
    return edges[:-1][keep], edges[1:][keep]


def hash_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each span's bytes."""
    forward, backward = powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * forward[: len(data)], out=total[1:])
        return mix((total[ends] - total[starts]) * backward[starts] + (ends - starts).astype(np.uint64))
