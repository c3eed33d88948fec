"""Back from unique keys to the edges they came from: a stored reverse index, or a join just in time."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from detspark.functions.schema import ProblemSpec
from detspark.operators.dedup import exchange, key_names, route
from detspark.plans.scratch import staged


def with_uid(unique: DataFrame) -> DataFrame:
    """``(words, part, uid)``: uid = part * 2^40 + rank inside the part."""
    names = key_names(unique)
    rank = F.row_number().over(Window.partitionBy("part").orderBy(*names[::-1])) - 1
    return unique.withColumn("uid", F.col("part").cast("long") * (1 << 40) + rank)


def stored(edges: DataFrame, unique: DataFrame, spec: ProblemSpec) -> DataFrame:
    """Edges with the uid of their target: the reverse index, joined once and kept."""
    return edges.join(with_uid(unique).select(*spec.names, "uid"), spec.names)


def by_uid(indexed: DataFrame, amps: DataFrame) -> DataFrame:
    """Amplitudes ``(uid, …)`` on edges that carry a uid."""
    return indexed.join(amps, "uid")


def jit(edges: DataFrame, amps: DataFrame, spec: ProblemSpec, cuts: np.ndarray | None = None, parts: int | None = None) -> DataFrame:
    """Edges joined with the amplitudes of their targets, nothing stored.

    With the splitters that laid out ``amps`` (which then has ``part``), edges take the same exchange and the join is on
    (key, part): the amplitudes are not hashed anew.  Otherwise it is a plain equi-join.
    """
    values = [c for c in amps.columns if c not in (*spec.names, "part")]
    if cuts is None:
        return edges.join(amps.select(*spec.names, *values), spec.names)
    left = exchange(route(edges, cuts), parts)
    right = exchange(amps.select(*spec.names, "part", *values), parts)
    return left.join(right.hint("merge"), [*spec.names, "part"]).drop("part")


def jit_batches(edges: DataFrame, amps: DataFrame, spec: ProblemSpec, batches: int) -> Iterator[DataFrame]:
    """The same in ``batches`` slices of the sources, one at a time."""
    slot = F.pmod(F.xxhash64(*spec.source_names), F.lit(batches))
    for b in range(batches):
        yield jit(edges.where(slot == b), amps, spec)


def slice_broadcast(edges: DataFrame, amps: DataFrame, spec: ProblemSpec, part: int, limit: int = 200_000) -> DataFrame:
    """One key range of the amplitudes sent to all tasks, if it has at most ``limit`` rows; else a shuffled join."""
    piece = amps.where(F.col("part") == part).drop("part")
    small = piece.limit(limit + 1).count() <= limit
    return edges.join(F.broadcast(piece) if small else piece, spec.names)


def keys_only(edges: DataFrame, spec: ProblemSpec, tag: str = "edges") -> tuple[DataFrame, DataFrame]:
    """Edges moved to files, and a scan of their keys alone: column pruning reads nothing else."""
    cold = staged(edges, tag)
    return cold, cold.select(*spec.names)
