"""Shared steps of the embedding operators: which vectors count, and their bytes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def widths(frame: DataFrame, column: str = "embedding") -> list[int]:
    """The numbers of components that occur, most frequent first; null and empty vectors are left out."""
    found = frame.where(F.size(column) > 0).groupBy(F.size(column).alias("d")).count().orderBy(F.desc("count"), F.desc("d")).collect()
    return [int(r["d"]) for r in found]


def matrix(column: pa.Array | pa.ChunkedArray, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows, values): rows of a list column with ``d`` components, none null or non-finite, as doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column) or not d:
        return np.zeros(0, np.int64), np.zeros((0, d))
    lengths = np.asarray(pc.list_value_length(column).fill_null(-1))
    rows = np.flatnonzero(lengths == d)
    if not len(rows):
        return rows, np.zeros((0, d))
    flat = column.take(pa.array(rows)).flatten().cast(pa.float64())
    values = np.asarray(flat.fill_null(np.nan)).reshape(-1, d) + 0.0  # one zero, not two
    good = np.isfinite(values).all(axis=1)
    return rows[good], values[good]


def usable(frame: DataFrame, d: int, id_column: str = "vec_id") -> DataFrame:
    """``(vec_id, embedding)`` → ``(vec_id, v)``, v the little-endian doubles of each vector that counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, values = matrix(batch.column(1), d)
            raw = values.astype("<f8").tobytes()
            cells = [raw[i : i + 8 * d] for i in range(0, len(raw), 8 * d)] if d else []
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows)), pa.array(cells, pa.binary())], [id_column, "v"])

    return frame.select(id_column, "embedding").mapInArrow(run, f"{id_column} {frame.schema[id_column].dataType.simpleString()}, v binary")


def stacked(column: pa.Array, d: int) -> np.ndarray:
    """The doubles of a binary column as a matrix."""
    return np.frombuffer(b"".join(column.to_pylist()), "<f8").reshape(-1, d)


def levelled(x: np.ndarray) -> np.ndarray:
    """Each row times the power of two that brings its largest component near 1: cosines stay, norms can't overflow or vanish."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])
