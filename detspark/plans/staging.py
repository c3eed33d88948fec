"""Stages with two barriers, bounded batches, overlap and offload."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.functions.ansatz import Model
from detspark.operators import baseline, dedup, energy, generate, infer, remap, topk
from detspark.operators.dedup import key_names
from detspark.operators.excite import Tables
from detspark.operators.metrics import StageTimer
from detspark.plans.scratch import Workspace


@dataclass(frozen=True)
class StageConfig:
    """Strategies of one iteration.

    ``regenerate``: edges are generated anew in the last stage instead of being stored.  ``sources``: sources in a batch of
    generation and of the last stage (all at once if None), cut by key ranges.  ``slices``: batches of key ranges in which the unique
    keys go through the model.  ``inflight``: batches under way at a time, so that one is read or written while another computes.
    """

    parts: int = 8
    batch: int = 4096
    k: int = 64
    eps: float = 0.0
    generation: str = "join"
    dedup: str = "range"
    regenerate: bool = False
    rebalance: str | None = None
    samples: int | None = None
    sources: int | None = None
    slices: int = 1
    inflight: int = 2


#: the staged engine and the hybrid baseline: same algorithm, host generation and central duplicate removal
ENGINE = StageConfig()
HYBRID = StageConfig(generation="rowwise", dedup="central")


def generated(space: DataFrame, t: Tables, cfg: StageConfig) -> DataFrame:
    keys = space.select(*t.spec.names)
    forms: dict[str, Callable[[], DataFrame]] = {
        "join": lambda: generate.by_join(keys, t, eps=cfg.eps), "virtual": lambda: generate.virtual(keys, t, eps=cfg.eps),
        "batch": lambda: generate.by_batch(keys, t, eps=cfg.eps), "rowwise": lambda: baseline.generate_rowwise(keys, t),
    }
    return forms[cfg.generation]()


def deduplicated(keys: DataFrame, cfg: StageConfig) -> tuple[DataFrame, np.ndarray | None]:
    """Distinct keys by the strategy, with a ``part`` column; all give the same set.  Key ranges also give their cuts."""
    if cfg.dedup == "range" and not cfg.rebalance:
        return dedup.range_laid(keys, cfg.parts, cfg.samples)
    forms: dict[str, Callable[[], DataFrame]] = {
        "range": lambda: dedup.range_sampled(keys, cfg.parts, cfg.samples, rebalance=cfg.rebalance), "native": lambda: dedup.range_native(keys, cfg.parts),
        "hash": lambda: baseline.dedup_hash(keys), "salted": lambda: baseline.dedup_salted(keys, cfg.parts), "central": lambda: baseline.dedup_central(keys, cfg.parts),
    }
    out = forms[cfg.dedup]()
    return (out if "part" in out.columns else out.withColumn("part", F.spark_partition_id())), None


@dataclass
class Stage1:
    """Batches of sources and of their edges (none if they are generated anew), the unique keys, and the cuts of their ranges if they have any."""

    sources: list[DataFrame]
    edges: list[DataFrame]
    unique: DataFrame
    cuts: np.ndarray | None = None

    @property
    def all_edges(self) -> DataFrame | None:
        return reduce(DataFrame.unionByName, self.edges) if self.edges else None


def stage1(space: DataFrame, t: Tables, cfg: StageConfig, timer: StageTimer, iteration: int = 0, work: Workspace | None = None) -> Stage1:
    """Generation, source batch by source batch, and global duplicate removal; ends with the first barrier (both results are files).

    Edges go to files at once; duplicate removal reads nothing but their keys.
    """
    work = work or Workspace(space.sparkSession)
    with timer.stage(iteration, "generation"):
        slices = list(batches(space.select(*t.spec.names), cfg.sources)) if cfg.sources else [space.select(*t.spec.names)]
        pairs = overlap([lambda piece=piece: offload(generated(piece, t, cfg), t, work) for piece in slices], cfg.inflight)
    with timer.stage(iteration, "dedup"):
        unique, cuts = deduplicated(reduce(DataFrame.unionByName, [keys for _, keys in pairs]), cfg)
        unique = work.staged(unique, "unique")
    if cfg.regenerate:
        work.drop("edges")
    return Stage1(slices, [] if cfg.regenerate else [edges for edges, _ in pairs], unique, cuts)


def stage2(unique: DataFrame, model: Model, t: Tables, cfg: StageConfig, timer: StageTimer, space: DataFrame, iteration: int = 0, work: Workspace | None = None) -> tuple[DataFrame, DataFrame]:
    """Inference on unique keys, slice by slice of their ranges, with the top-K of each slice of those not in the space yet; ends with the second barrier."""
    work = work or Workspace(unique.sparkSession)
    names = t.spec.names

    def infer_slice(i: int) -> tuple[DataFrame, DataFrame]:
        mine = unique.where(F.col("part") % cfg.slices == i) if cfg.slices > 1 else unique
        amps = work.staged(infer.run(mine, model, t.spec, cfg.batch), "amps")
        fresh = amps.join(space.select(*names), names, "left_anti").withColumn("score", F.col("log_abs"))
        return amps, work.staged(topk.two_level(fresh, cfg.k, batch=cfg.batch), "best")

    with timer.stage(iteration, "inference"):
        done = overlap([lambda i=i: infer_slice(i) for i in range(cfg.slices)], cfg.inflight)
    with timer.stage(iteration, "other"):
        top = work.staged(topk.exact(reduce(DataFrame.unionByName, [b for _, b in done]), cfg.k), "top")
        work.drop("best")
    return reduce(DataFrame.unionByName, [a for a, _ in done]), top


def stage3(first: Stage1, amps: DataFrame, space: DataFrame, t: Tables, cfg: StageConfig, timer: StageTimer, iteration: int = 0, work: Workspace | None = None, inside: bool = False) -> tuple[DataFrame, dict]:
    """Amplitudes back on the edges just in time, batch by batch of sources; local and global energies.

    With the cuts of the unique keys, edges take the ranges in which the amplitudes lie and the join is on (key, part).
    Sources are whole in a batch, so local energies of batches are put together as they are.  ``inside``: only edges whose target is in the space.
    """
    work = work or Workspace(space.sparkSession)
    spec = t.spec

    def energies(i: int) -> DataFrame:
        edges = first.edges[i] if first.edges else generated(first.sources[i], t, cfg)
        if inside:
            edges = edges.join(space.select(*spec.names), spec.names, "left_semi")
        joined = remap.jit(edges, values, spec, first.cuts, cfg.parts)
        return work.staged(energy.local(joined, values, spec, joined=True), "local")

    with timer.stage(iteration, "other"):
        values = energy.complex_amps(amps)
        if first.cuts is None:
            values = values.drop("part")
        local = reduce(DataFrame.unionByName, overlap([lambda i=i: energies(i) for i in range(len(first.sources))], cfg.inflight))
        total = energy.total(local).first().asDict()
    return local, total


def batches(frame: DataFrame, rows: int, total: int | None = None) -> Iterator[DataFrame]:
    """``frame`` in key-range slices of about ``rows`` rows each; on a staged, sorted table a slice reads only its files' ranges."""
    names = key_names(frame)
    total = frame.count() if total is None else total
    count = max(1, -(-total // rows))
    cuts = dedup.splitters(dedup.regular_sample(frame, min(8 * count, dedup.SAMPLES)), count)
    highest = names[-1]
    edges: list[np.ndarray | None] = [None, *cuts, None]
    for lo, hi in zip(edges, edges[1:], strict=False):
        part = frame
        key = F.struct(*names[::-1])
        for bound, op in ((lo, "ge"), (hi, "lt")):
            if bound is None:
                continue
            limit = F.struct(*[F.lit(int(x)).cast("long").alias(n) for n, x in zip(names[::-1], bound[::-1], strict=True)])
            coarse = F.col(highest) >= int(bound[-1]) if op == "ge" else F.col(highest) <= int(bound[-1])  # pushed to the scan
            part = part.where(coarse).where(key >= limit if op == "ge" else key < limit)
        yield part


def overlap(jobs: list[Callable[[], object]], n_inflight: int = 2) -> list[object]:
    """Run jobs with at most ``n_inflight`` at a time, so one reads while another computes or writes; results in order."""
    if len(jobs) < 2 or n_inflight < 2:
        return [job() for job in jobs]
    with ThreadPoolExecutor(n_inflight) as pool:
        return list(pool.map(lambda job: job(), jobs))


def offload(edges: DataFrame, t: Tables, work: Workspace | None = None) -> tuple[DataFrame, DataFrame]:
    """Edges to files; what duplicate removal and inference need is a scan of their key columns."""
    if work is None:
        return remap.keys_only(edges, t.spec)
    cold = work.staged(edges, "edges")
    return cold, cold.select(*t.spec.names)


def batch_bytes(frame: DataFrame, rows: int) -> int:
    """Largest bytes that a batch of at most ``rows`` rows of fixed-width columns holds."""
    width = sum({"bigint": 8, "double": 8, "int": 4, "tinyint": 1, "boolean": 1}.get(kind, 16) for _, kind in frame.dtypes)
    return rows * width
