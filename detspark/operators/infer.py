"""Batched inference: the model runs once per unique key."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from detspark.functions import bits
from detspark.functions.ansatz import Model
from detspark.functions.schema import ProblemSpec


def run(unique: DataFrame, model: Model, spec: ProblemSpec, batch: int = 4096) -> DataFrame:
    """``unique`` with ``log_abs, phase``; at most ``batch`` rows are in the model at a time; no shuffle, so the key ranges stay."""
    held = unique.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([*unique.schema.fields, T.StructField("log_abs", T.DoubleType()), T.StructField("phase", T.DoubleType())])
    names, m = spec.names, spec.m

    def forward(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, batch):
                part = whole.slice(at, batch)
                words = np.stack([part.column(part.schema.get_field_index(c)).to_numpy() for c in names], 1)
                log, phase = held.value.forward(bits.to_bits(words, m))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(log), pa.array(phase)], schema.names)

    return unique.mapInArrow(forward, schema)
