"""The outer loop: generate, infer, select, measure, optimise; stage by stage with files between iterations."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark.functions.ansatz import Model, Params
from detspark.functions.schema import HISTORY
from detspark.operators import exact, optimize
from detspark.operators.excite import Tables, tables
from detspark.operators.metrics import StageTimer
from detspark.operators.space import grow, reference
from detspark.plans.scratch import Workspace
from detspark.plans.staging import ENGINE, HYBRID, StageConfig, stage1, stage2, stage3
from detspark.sources.hamiltonian import Hamiltonian


@dataclass(frozen=True)
class LoopConfig:
    """Stops after ``iterations`` or once the energy changed by less than ``tol`` over ``window`` steps.

    ``cool``: the learning rate falls to 0 over the second half of an iteration's steps, and the optimizer starts anew where the
    space has grown, as old moments belong to other gradients.  ``inner``: further optimizer steps of each iteration on the space as it is, by its matrix, for spaces that one process
    can hold.  ``rounds`` of growth come first; after them the space stays.
    """

    stages: StageConfig = ENGINE
    iterations: int = 10
    tol: float = 1e-6
    window: int = 3
    lr: float = 3e-4
    decay: float = 0.01
    max_size: int | None = None
    variational: bool = True
    inner: int = 0
    rounds: int | None = None
    cool: bool = False


@dataclass
class RunResult:
    """``energies``: of each iteration, over the cluster; ``trajectory``: of every optimizer step, the inner ones included."""

    history: DataFrame
    space: DataFrame
    params: Params
    timer: StageTimer = field(default_factory=StageTimer)
    energies: list[float] = field(default_factory=list)
    trajectory: list[float] = field(default_factory=list)


def run(spark: SparkSession, ham: Hamiltonian, model: Model, cfg: LoopConfig = LoopConfig(), start: DataFrame | None = None) -> RunResult:
    """Lowest energy by growing a space and training ``model`` on it.

    Each iteration ends in files, so lineage does not grow, and a lost executor recomputes one stage at most.  Files of an
    iteration are deleted when their last reader is done.
    """
    spec, t = ham.spec, tables(ham, cfg.stages.eps)
    timer, optimizer = StageTimer(), optimize.AdamW(lr=cfg.lr, decay=cfg.decay)
    base = reference(spark, spec) if start is None else start
    spaces = Workspace(spark)
    space = spaces.staged(base.select(*spec.names, F.lit(0).alias("iter_added"), F.lit(0.0).alias("score")), "space0")
    history, energies, trajectory = [], [], []
    for i in range(cfg.iterations):
        work = Workspace(spark)
        if cfg.cool:
            optimizer = optimize.AdamW(lr=cfg.lr, decay=cfg.decay)
        first = stage1(space, t, cfg.stages, timer, i, work)
        amps, top = stage2(first.unique, model, t, cfg.stages, timer, space, i, work)
        local, total = stage3(first, amps, space, t, cfg.stages, timer, i, work, inside=cfg.variational)
        with timer.stage(i, "other"):
            grads = optimize.gradient(local, total["energy"], total["norm"], model, spec)
            _warm(optimizer, cfg)
            model.params = optimizer.step(model.params, grads)
            trajectory.append(float(total["energy"]))
            trajectory += _inner(space, t, model, optimizer, cfg)
        seconds = {}
        for it, name, s in timer.rows:
            if it == i:
                seconds[name] = seconds.get(name, 0.0) + s
        edges = first.all_edges
        history.append((i, float(total["energy"]), float(total["variance"]), total["n"], edges.count() if edges is not None else 0, first.unique.count(), seconds))
        energies.append(float(total["energy"]))
        if len(energies) > cfg.window and max(abs(a - b) for a, b in zip(energies[-cfg.window :], energies[-cfg.window - 1 : -1], strict=True)) < cfg.tol:
            work.drop(*list(work.paths))
            break
        if cfg.rounds is None or i < cfg.rounds:
            space = spaces.staged(grow(space, top, spec, i + 1, max_size=cfg.max_size), f"space{i + 1}")
            spaces.drop(f"space{i}")
        work.drop(*list(work.paths))
    return RunResult(spark.createDataFrame(history, HISTORY), space, model.params, timer, energies, trajectory)


def _inner(space: DataFrame, t: Tables, model: Model, optimizer: optimize.AdamW, cfg: LoopConfig) -> list[float]:
    """Energies of the inner steps, whose gradients come from the matrix of the space; rows in the order the engine stored them."""
    if not cfg.inner:
        return []
    rows = space.select(*t.spec.names).limit(exact.DENSE_LIMIT + 1).collect()
    words = np.array([tuple(r) for r in rows], np.int64)
    h = exact.dense_matrix(t, words)
    return _steps(model, words, h, t.spec.m, cfg.inner, optimizer, cfg)


def _warm(optimizer: optimize.AdamW, cfg: LoopConfig) -> None:
    """The learning rate of the next step."""
    if cfg.cool:
        optimizer.lr = cfg.lr * min(1.0, 2 * (1 - optimizer.t / (cfg.inner + 1)))


def _steps(model: Model, words: np.ndarray, h: np.ndarray, m: int, steps: int, optimizer: optimize.AdamW, cfg: LoopConfig = LoopConfig()) -> list[float]:
    out = []
    for _ in range(steps):
        out.append(optimize.dense_energy(model, words, h, m))
        _warm(optimizer, cfg)
        model.params = optimizer.step(model.params, optimize.dense_gradient(model, words, h, m))
    return out


def ablation(spark: SparkSession, space: DataFrame, t: Tables, model: Model, cfg: StageConfig = ENGINE) -> DataFrame:
    """``variant, stage, seconds, energy``: the hybrid baseline, then with engine generation, then also with engine duplicate removal.

    Sources are dealt out first, as all forms of generation follow the partitions of the space, and a small set is one file.
    """
    rows = []
    space = space.repartition(max(cfg.parts, 2 * spark.sparkContext.defaultParallelism))
    for name, config in (("hybrid", HYBRID), ("+generation", replace(HYBRID, generation=cfg.generation)), ("+dedup", cfg)):
        config = replace(config, parts=cfg.parts, batch=cfg.batch, k=cfg.k)
        timer = StageTimer()
        first = stage1(space, t, config, timer)
        amps, _ = stage2(first.unique, model, t, config, timer, space)
        _, total = stage3(first, amps, space, t, config, timer)
        rows += [(name, stage, s, float(total["energy"])) for _, stage, s in timer.rows]
    frame = spark.createDataFrame(rows, "variant string, stage string, seconds double, energy double")
    return frame.groupBy("variant", "stage").agg(F.sum("seconds").alias("seconds"), F.first("energy").alias("energy"))


def dense_history(model: Model, words: np.ndarray, h: np.ndarray, m: int, steps: int, lr: float = 3e-4, decay: float = 0.0) -> list[float]:
    """Energies of training on a fixed small space by matrix: the many-step companion of ``run``."""
    return _steps(model, words, h, m, steps, optimize.AdamW(lr=lr, decay=decay))
