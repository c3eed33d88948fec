"""The K largest amplitudes; ties go to the smaller key."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detspark.operators.dedup import key_names


def _order(frame: DataFrame, score: str) -> list[Column]:
    return [F.desc(score), *[F.col(c) for c in key_names(frame)[::-1]]]


def exact(amps: DataFrame, k: int, score: str = "score") -> DataFrame:
    """``words, score`` of the K largest scores: a bounded heap per task and one merge."""
    return amps.select(*key_names(amps), score).orderBy(*_order(amps, score)).limit(k)


def two_level(amps: DataFrame, k: int, score: str = "score", batch: int = 10_000) -> DataFrame:
    """First the K best of each batch of a task, kept in a running set, then the K best of those; memory follows K + batch."""
    names = key_names(amps)
    kept = amps.select(*names, score)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: pa.Table | None = None
        for whole in batches:
            for at in range(0, whole.num_rows, batch):
                part = pa.Table.from_batches([whole.slice(at, batch)])
                both = part if best is None else pa.concat_tables([best, part])
                value = both.column(score).to_numpy()
                order = np.lexsort((*[both.column(c).to_numpy() for c in names], -value))[:k]
                best = both.take(pa.array(order)).combine_chunks()
        if best is not None and k > 0:
            yield from best.to_batches()

    return exact(kept.mapInArrow(run, kept.schema), k, score)


def running(batches: Iterable[DataFrame], k: int, score: str = "score", prune: bool = True) -> DataFrame | None:
    """A global set refined batch by batch; with ``prune`` a batch first drops what lies below the K-th score so far.

    The set is K rows on the driver side of each round; use it for K that fits there.
    """
    best: DataFrame | None = None
    for part in batches:
        names = key_names(part)
        part = part.select(*names, score)
        if best is not None and prune:
            floor = best.agg(F.count("*"), F.min(score)).first()
            if floor[0] >= k:
                part = part.where(F.col(score) >= floor[1])
        rows = exact(part if best is None else best.unionByName(part), k, score).collect()
        best = part.sparkSession.createDataFrame(rows, part.schema)
    return best


def first_rows(frame: DataFrame, order: list[Column], k: int, parts: int = 64) -> DataFrame:
    """The first ``k`` rows in an order, for a k that no single task can hold: ranges are taken whole, the last one is cut exactly."""
    from detspark.plans.scratch import staged

    ranged = staged(frame.repartitionByRange(parts, *order).withColumn("_p", F.spark_partition_id()), "ranges")
    counts = sorted((r["_p"], r["count"]) for r in ranged.groupBy("_p").count().collect())
    taken, last, whole = 0, None, []
    for p, n in counts:
        if taken + n > k:
            last = p
            break
        whole.append(p)
        taken += n
    out = ranged.where(F.col("_p").isin(whole)).drop("_p")
    return out if last is None else out.unionByName(ranged.where(F.col("_p") == last).drop("_p").orderBy(*order).limit(k - taken))


def large(amps: DataFrame, k: int, score: str = "score", parts: int = 64) -> DataFrame:
    """For a K that fits no single task: score ranges are taken whole from the top, the last one is cut exactly."""
    return first_rows(amps.select(*key_names(amps), score), _order(amps, score), k, parts)
