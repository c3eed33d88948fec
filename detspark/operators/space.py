"""Configuration spaces: full enumeration, starting points, growth."""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.schema import BITS, ProblemSpec, require, space_schema
from detspark.operators.topk import first_rows


def binomials(m: int, n: int) -> np.ndarray:
    """``[p, k]``: configurations of k particles in p orbitals, p < m and k <= n; those beyond 64 bits as the largest number."""
    top = np.iinfo(np.int64).max
    return np.array([[min(comb(p, k), top) for k in range(n + 1)] for p in range(m)], np.int64).reshape(m, n + 1)


def unrank(index: np.ndarray, m: int, n: int) -> np.ndarray:
    """Configurations by their place in numeric order (combinatorial number system), as a word matrix."""
    ways, rest = binomials(m, n), np.array(index, np.int64)
    words = np.zeros((len(rest), max(1, -(-m // BITS))), np.int64)
    one = np.array([bits.mask_words([p], m) for p in range(m)], np.int64).reshape(m, words.shape[1])
    for k in range(n, 0, -1):
        p = np.searchsorted(ways[:, k], rest, "right") - 1  # the highest orbital below which k particles have no more places than that
        rest -= ways[p, k]
        words |= one[p]
    return words


def enumerate_space(spark: SparkSession, spec: ProblemSpec, sector: tuple[int, int] | None = None, partitions: int | None = None) -> DataFrame:
    """All configurations, or those with the given numbers of even- and odd-orbital particles.

    Up to 25 orbitals: a filtered range, all in the JVM.  Above: a range of ranks, unranked in batches.
    """
    m, n, names = spec.m, spec.n, spec.names
    if m <= 25:
        frame = spark.range(0, 1 << m, numPartitions=partitions).where(F.bit_count("id") == n).select(F.col("id").alias("w0"))
    else:

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                words = unrank(batch.column(0).to_numpy(), m, n)
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(words[:, k])) for k in range(len(names))], names)

        frame = spark.range(0, comb(m, n), numPartitions=partitions).mapInArrow(run, space_schema(spec))
    if sector is None:
        return frame
    even = [F.lit(w).cast("long") for w in bits.mask_words(list(range(0, m, 2)), m)]
    return frame.where(bits.overlap([F.col(c) for c in names], even) == sector[0]).where(F.lit(sum(sector) == n))


def reference(spark: SparkSession, spec: ProblemSpec) -> DataFrame:
    """One row: the lowest orbitals filled."""
    words = bits.mask_words(list(range(spec.n)), spec.m)
    return spark.range(1).select(*[F.lit(w).cast("long").alias(c) for w, c in zip(words, spec.names, strict=True)])


def checked(frame: DataFrame, spec: ProblemSpec) -> DataFrame:
    """``frame`` that fails on a row without exactly ``n`` ones; evaluated with the rows, not as a job of its own."""
    require(frame, spec.names)
    count = bits.popcount([F.col(c) for c in spec.names])
    return frame.where(F.when(count == spec.n, F.lit(True)).otherwise(F.raise_error(F.lit("configuration with a wrong number of ones")).cast("boolean")))


#: more rows than this are cut to size by ranges and not in one task
ONE_TASK = 1_000_000


def grow(space: DataFrame, top: DataFrame, spec: ProblemSpec, iteration: int = 0, replace: bool = False, max_size: int | None = None) -> DataFrame:
    """``space`` (words, iter_added, score) with the configurations of ``top`` (words, score) that it lacks.

    ``max_size`` keeps the best by score, then key; with ``replace`` rows of ``space`` compete by their score too, else
    they always stay and only additions are cut.
    """
    names = spec.names
    new = top.join(space.select(*names), names, "left_anti").select(*names, F.lit(iteration).alias("iter_added"), "score")
    both = space.select(*names, "iter_added", "score").unionByName(new)
    if max_size is None:
        return both
    first = F.lit(0) if replace else F.when(F.col("iter_added") == iteration, 1).otherwise(0)
    marked, order = both.withColumn("_f", first), [F.col("_f"), F.desc_nulls_last("score"), *[F.col(w) for w in spec.order]]
    cut = marked.orderBy(*order).limit(max_size) if max_size <= ONE_TASK else first_rows(marked, order, max_size, -(-max_size // ONE_TASK) * 4)
    return cut.drop("_f")
