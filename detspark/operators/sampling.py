"""Sampling baseline: configurations drawn from |psi|², energy from the distinct samples with their counts."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.ansatz import Transformer
from detspark.functions.schema import ProblemSpec
from detspark.operators import energy as en
from detspark.operators import generate, infer
from detspark.operators.dedup import range_sampled
from detspark.operators.excite import Tables
from detspark.plans.scratch import staged


def draw(spark: SparkSession, model: Transformer, spec: ProblemSpec, samples: int, seed: int = 0, chunks: int = 8, levels: int = 4) -> DataFrame:
    """``(words, count)`` of ``samples`` draws, orbital by orbital: a prefix holds a count, which is split by the conditional.

    Equal prefixes of different chunks are merged every few orbitals.  The draws of a prefix depend on the seed, the chunk
    and the prefix, so reruns agree.
    """
    m, names = spec.m, spec.names
    share = [samples // chunks + (i < samples % chunks) for i in range(chunks)]
    frame = spark.createDataFrame([(i, *[0] * len(names), c) for i, c in enumerate(share) if c], "chunk int, " + ", ".join(f"{w} long" for w in names) + ", count long")
    held = spark.sparkContext.broadcast(model)
    schema = frame.schema

    def extend(low: int, high: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if not batch.num_rows:
                    continue
                chunk = batch.column(0).to_numpy()
                x = bits.to_bits(np.stack([batch.column(1 + k).to_numpy() for k in range(len(names))], 1), m)
                count = batch.column(len(names) + 1).to_numpy()
                for t in range(low, high):
                    p = np.clip(held.value.conditionals(x)[:, t], 0.0, 1.0)
                    words = bits.from_bits(x)
                    ones = np.array([np.random.default_rng([seed, int(c), t, *map(int, w)]).binomial(int(k), q) for c, w, k, q in zip(chunk, words, count, p, strict=True)], np.int64)
                    up = x.copy()
                    up[:, t] = 1
                    chunk, x, count = np.concatenate([chunk, chunk]), np.concatenate([x, up]), np.concatenate([count - ones, ones])
                    live = count > 0
                    chunk, x, count = chunk[live], x[live], count[live]
                words = bits.from_bits(x)
                columns = [pa.array(chunk.astype(np.int32)), *[pa.array(np.ascontiguousarray(words[:, k])) for k in range(len(names))], pa.array(count)]
                yield pa.RecordBatch.from_arrays(columns, schema.names)

        return run

    step = -(-m // levels)
    for low in range(0, m, step):
        frame = frame.repartition(chunks, "chunk", *names).mapInArrow(extend(low, min(m, low + step)), schema)
        frame = frame.groupBy("chunk", *names).agg(F.sum("count").alias("count")).select(*schema.names)
        frame = staged(frame, "prefixes")
    return frame.groupBy(*names).agg(F.sum("count").alias("count"))


def energy(drawn: DataFrame, model: Transformer, t: Tables, parts: int = 8) -> DataFrame:
    """``energy, error, distinct, total``: count-weighted mean of the local energies and its standard error."""
    spec = t.spec
    drawn = staged(drawn, "drawn")
    edges = staged(generate.by_join(drawn, t), "edges")
    unique = range_sampled(edges.select(*spec.names), parts)
    amps = en.complex_amps(staged(infer.run(unique, model, spec), "amps"))
    local = en.local(edges, amps, spec)
    counted = local.join(drawn.select(*[F.col(w).alias(s) for w, s in zip(spec.names, spec.source_names, strict=True)], "count"), spec.source_names)
    n, e = F.sum("count"), F.sum(F.col("count") * F.col("eloc_re")) / F.sum("count")
    sq = F.sum(F.col("count") * F.col("eloc_re") * F.col("eloc_re")) / F.sum("count")
    return counted.agg(e.alias("energy"), F.sqrt(F.greatest(sq - e * e, F.lit(0.0)) / n).alias("error"), F.count("*").alias("distinct"), n.alias("total"))
