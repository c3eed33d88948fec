"""Moves made and made unique in spaces of which a task can hold one bit per configuration.

The steps are those of ``dedup``: the distinct keys of each task as a sorted run, a regular sample of the runs, splitters, one
exchange, compaction.  A run is a bitmap over the ranks of the configurations, whose order is the order of the keys: sorting
and local removal are one write per key, and what is sampled, cut, exchanged and compacted are pieces of bitmaps.  No key
leaves its task before its copies there are gone, and a run has the size of the space however many sources there are.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.schema import ProblemSpec, require
from detspark.operators import dedup
from detspark.operators.space import binomials, unrank
from detspark.plans.scratch import staged

#: configurations of the largest space that is handled this way; a task holds a byte for each while it marks them
LIMIT = 1 << 27
#: ranks in a piece of a bitmap
PIECE = 1 << 16
#: sources whose moves are ranked at a time, and pieces in a batch
BLOCK, ROWS = 128, 256


def fits(spec: ProblemSpec) -> bool:
    return comb(spec.m, spec.n) <= LIMIT


def rank(words: np.ndarray, spec: ProblemSpec) -> np.ndarray:
    """Places of configurations in key order; the inverse of ``unrank``."""
    ways, occ = binomials(spec.m, spec.n), bits.occupied_rows(words, spec.m, spec.n)
    return ways[occ, np.arange(1, spec.n + 1)].sum(1) if spec.n else np.zeros(len(words), np.int64)


def _prefix(rest: np.ndarray, ways: np.ndarray, more: int) -> np.ndarray:
    """Running sums, from 0, of what the remaining particles give to a rank if ``more`` new ones lie below them."""
    terms = ways[rest, np.arange(1, rest.shape[1] + 1) + more]
    return np.concatenate([np.zeros((len(rest), 1), np.int64), np.cumsum(terms, 1)], 1)


def moved_ranks(words: np.ndarray, spec: ProblemSpec, kinds: tuple[int, ...] = (1, 2)) -> Iterator[np.ndarray]:
    """Ranks of the targets of all one- and two-particle moves of some sources, every target of every source.

    With the particles that stay fixed, the rank of a target is a sum of one term for each new particle: its own, and what the
    particles above it gain by being one place higher.  So a pair of new orbitals a < b is an entry of x[a] + y[b].
    """
    m, n = spec.m, spec.n
    ways, occ = binomials(m, n), bits.occupied_rows(words, m, n)
    empty = np.nonzero(bits.to_bits(words, m) == 0)[1].reshape(len(words), m - n)
    for kind in kinds:
        if n < kind or m - n < kind:
            continue
        stay = np.array(list(combinations(range(n), n - kind)), np.int64).reshape(comb(n, kind), n - kind)
        rest = occ[:, stay].reshape(len(words) * len(stay), n - kind)  # a row for each source and choice of the particles that stay
        free = np.repeat(empty, len(stay), 0)
        below = (rest[:, :, None] < free[:, None, :]).sum(1)
        plain, one = (_prefix(rest, ways, k) for k in (0, 1))
        at = lambda sums: np.take_along_axis(sums, below, 1)
        x = ways[free, below + 1] + at(plain) - at(one)
        if kind == 1:
            yield (x + one[:, -1:]).ravel()
            continue
        two = _prefix(rest, ways, 2)
        y = ways[free, below + 2] + at(one) - at(two) + two[:, -1:]
        for a in range(m - n - 1):
            yield (x[:, a : a + 1] + y[:, a + 1 :]).ravel()


def _members(piece: bytes) -> np.ndarray:
    """Ranks in a piece, from its start."""
    return np.flatnonzero(np.unpackbits(np.frombuffer(piece, np.uint8), bitorder="little"))


def _packed(marks: np.ndarray) -> bytes:
    return np.packbits(marks, bitorder="little").tobytes()


def _batches(rows: Iterator[tuple], schema: pa.Schema, size: int = ROWS) -> Iterator[pa.RecordBatch]:
    held = []
    for row in rows:
        held.append(row)
        if len(held) == size:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)
            held = []
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)


RUN = pa.schema([("run", pa.int32()), ("piece", pa.int32()), ("bits", pa.binary()), ("n", pa.int64()), ("before", pa.int64()), ("total", pa.int64())])
ROUTED = pa.schema([("part", pa.int32()), ("piece", pa.int32()), ("bits", pa.binary())])
UNIQUE = pa.schema([*ROUTED, ("n", pa.int64())])
_RUN, _ROUTED = "run int, piece int, bits binary, n long, before long, total long", "part int, piece int, bits binary"
_UNIQUE = f"{_ROUTED}, n long"


def runs(sources: DataFrame, spec: ProblemSpec, kinds: tuple[int, ...] = (1, 2)) -> DataFrame:
    """Distinct moves of each task: pieces of its bitmap that are not empty, with their keys ``n``, the keys of the run ``before`` the piece and in ``total``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = None
        for batch in batches:
            words = np.stack([c.to_numpy() for c in batch.columns], 1)
            for at in range(0, len(words), BLOCK):
                seen = np.zeros(-(-comb(spec.m, spec.n) // PIECE) * PIECE, bool) if seen is None else seen
                for ranks in moved_ranks(words[at : at + BLOCK], spec, kinds):
                    seen[ranks] = True
        if seen is not None:
            marks = seen.reshape(-1, PIECE)
            counts = np.count_nonzero(marks, 1)
            before, pid = np.cumsum(counts) - counts, TaskContext.get().partitionId()
            yield from _batches(((pid, int(i), _packed(marks[i]), int(counts[i]), int(before[i]), int(counts.sum())) for i in np.flatnonzero(counts)), RUN)

    return staged(require(sources, spec.names).select(*spec.names).mapInArrow(run, _RUN), "runs")


def sample_runs(laid: DataFrame, spec: ProblemSpec, s: int) -> DataFrame:
    """From each run of D keys those at places ``floor(k D / s)``, k = 0..s-1 (all if D < s): ``words, weight, pid``, as ``dedup.sample_runs`` has them."""
    names = spec.names
    schema = pa.schema([*[(w, pa.int64()) for w in names], ("weight", pa.float64()), ("pid", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                take = min(r["total"], s)
                k = np.arange(-(-r["before"] * take // r["total"]), -(-(r["before"] + r["n"]) * take // r["total"]))
                if len(k):
                    words = unrank(r["piece"] * PIECE + _members(r["bits"])[k * r["total"] // take - r["before"]], spec.m, spec.n)
                    yield pa.RecordBatch.from_arrays([*[pa.array(np.ascontiguousarray(words[:, i])) for i in range(len(names))], pa.array(np.full(len(k), r["total"] / take)), pa.array(np.full(len(k), r["run"], np.int32))], schema=schema)

    return staged(laid.mapInArrow(run, f"{', '.join(f'{w} long' for w in names)}, weight double, pid int"), "samples")


def route(laid: DataFrame, cuts: np.ndarray) -> DataFrame:
    """Pieces with the range that they lie in; one that a cut goes through is split there."""
    cuts = np.asarray(cuts, np.int64)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for batch in batches:
            for piece, held in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                first, last = np.searchsorted(cuts, [piece * PIECE, (piece + 1) * PIECE - 1], "right")
                if first == last:
                    yield int(first), piece, held
                    continue
                inside = _members(held)
                parts = np.searchsorted(cuts, inside + piece * PIECE, "right")
                for p in np.unique(parts):
                    marks = np.zeros(PIECE, bool)
                    marks[inside[parts == p]] = True
                    yield int(p), piece, _packed(marks)

    return laid.select("piece", "bits").mapInArrow(lambda batches: _batches(rows(batches), ROUTED), _ROUTED)


def compact(routed: DataFrame) -> DataFrame:
    """Distinct keys of each part, as pieces in key order with their number of keys ``n``; no further shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for part, piece, marks in zip(*[batch.column(i).to_pylist() for i in range(3)], strict=True):
                marks = np.frombuffer(marks, np.uint8)
                if (part, piece) in held:
                    held[part, piece] |= marks
                else:
                    held[part, piece] = marks.copy()
        yield from _batches(((*at, marks.tobytes(), int(np.bitwise_count(marks).sum())) for at, marks in sorted(held.items(), key=lambda x: x[0])), UNIQUE)

    return routed.mapInArrow(run, _UNIQUE)


def range_unique(sources: DataFrame, spec: ProblemSpec, parts: int, s: int | None = None, kinds: tuple[int, ...] = (1, 2)) -> DataFrame:
    """The distinct moves of ``sources`` by sampled ranges, ``part, piece, bits, n``: ``dedup.range_sampled`` on bitmaps.

    Sources are dealt out first: their moves are what costs, and a set of them may lie in one partition.
    """
    if not fits(spec):
        raise ValueError(f"{comb(spec.m, spec.n)} configurations are more than {LIMIT}")
    tasks = max(parts, 2 * sources.sparkSession.sparkContext.defaultParallelism)
    laid = runs(sources.repartition(tasks), spec, kinds)
    cuts = dedup.splitters(sample_runs(laid, spec, s or min(8 * parts, dedup.SAMPLES)), parts)
    return compact(dedup.exchange(route(laid, rank(cuts, spec)), parts))


def keys(unique: DataFrame, spec: ProblemSpec) -> DataFrame:
    """The configurations of ``range_unique``: ``words, part``, in key order within a part."""
    names = spec.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, piece, held in zip(*[batch.column(i).to_pylist() for i in range(3)], strict=True):
                words = unrank(piece * PIECE + _members(held), spec.m, spec.n)
                yield pa.RecordBatch.from_arrays([*[pa.array(np.ascontiguousarray(words[:, k])) for k in range(len(names))], pa.array(np.full(len(words), part, np.int32))], [*names, "part"])

    return unique.select("part", "piece", "bits").mapInArrow(run, f"{', '.join(f'{w} long' for w in names)}, part int")
