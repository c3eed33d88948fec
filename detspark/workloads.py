"""The experiment workloads on the given tables.  Each returns a table of its measures."""

from __future__ import annotations

import time
from dataclasses import replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.ansatz import ClosedForm, Rbm, Tabular, Transformer
from detspark.functions.schema import ProblemSpec
from detspark.operators import dedup, dense, exact, excite, generate, infer, metrics, optimize, sampling, space, topk
from detspark.plans import loop, staging
from detspark.plans.scratch import Workspace, staged
from detspark.sources import hamiltonian
from detspark.sources.tables import configuration_set, line_keys

#: key sources of the duplicate-removal experiments
SOURCES = ("emb20", "ord4", "evt3", "doc6", "lines")


def keys_of(spark: SparkSession, sf_dir: str, name: str, partitions: int = 16) -> tuple[DataFrame, int]:
    """Redundant keys of a source, staged, and their number."""
    if name == "lines":
        keys = line_keys(spark, sf_dir)
    else:
        spec, sources = configuration_set(spark, sf_dir, name)
        keys = generate.moves(sources.repartition(partitions), spec)
    keys = staged(keys, "keys")
    return keys, keys.count()


def small_problems(spark: SparkSession, sf_dir: str) -> list[hamiltonian.Hamiltonian]:
    return [
        hamiltonian.two_level_molecule(), hamiltonian.lattice(2, 2, ring=False), hamiltonian.lattice(4, 4), hamiltonian.lattice(6, 6),
        hamiltonian.table(spark, sf_dir, 8, 3), hamiltonian.table(spark, sf_dir, 12, 4),
    ]


def accuracy_small(spark: SparkSession, sf_dir: str, inner: int = 1500, sampled: int = 100) -> DataFrame:
    """``problem, method, step, exact, energy, error, within``: the energy error of every step against the exact answer.

    ``engine`` and ``hybrid`` are the whole loop with either set of strategies on all configurations of the problem (growth from
    the reference would need a round for every hop): energies of an iteration come over the cluster, and ``inner`` further steps
    are taken on its space.  ``sampling`` trains an autoregressive model by drawn configurations; its last row is the sampling
    baseline's energy over the cluster.  ``within`` uses 1.6e-3 where units are Hartree-like, and the same relative to a tenth of
    \\|exact\\| for the table problems.
    """
    rows = []
    for ham in small_problems(spark, sf_dir):
        t = excite.tables(ham)
        reference, _, words = exact.dense_ground(t)
        scale = max(1.0, abs(reference) / 10)
        found: dict[str, list[float]] = {}
        for method, stages in (("engine", staging.ENGINE), ("hybrid", staging.HYBRID)):
            cfg = loop.LoopConfig(stages=replace(stages, parts=2, k=len(words)), iterations=2, lr=0.05, decay=0.0, inner=inner, window=2, cool=True)
            found[method] = loop.run(spark, ham, Tabular.start(words), cfg, start=space.enumerate_space(spark, ham.spec)).trajectory
        h, model, rng = exact.dense_matrix(t, words), Transformer.start(ham.spec.m, ham.spec.n, width=16, layers=1, heads=2, hidden=16), np.random.default_rng(1)
        optimizer, found["sampling"] = optimize.AdamW(lr=0.02, decay=0.0), []
        for _ in range(sampled):
            found["sampling"].append(optimize.dense_energy(model, words, h, ham.spec.m))
            model.params = optimizer.step(model.params, sampled_gradient(model, words, h, ham.spec, 500, rng))
        found["sampling"].append(sampling.energy(sampling.draw(spark, model, ham.spec, 5000, chunks=2, levels=2), model, t, 2).first()["energy"])
        rows += [(ham.name, m, i, reference, float(e), abs(e - reference), bool(abs(e - reference) < 1.6e-3 * scale)) for m, steps in found.items() for i, e in enumerate(steps)]
    return spark.createDataFrame(rows, "problem string, method string, step int, exact double, energy double, error double, within boolean")


def sampled_gradient(model, words: np.ndarray, h: np.ndarray, spec: ProblemSpec, samples: int, rng: np.random.Generator) -> dict:
    """Gradient from configurations drawn by |psi|²: noisy, and blind to what is not drawn."""
    x = bits.to_bits(words, spec.m)
    log, phase = model.forward(x)
    psi = np.exp(log - log.max() + 1j * phase)
    p = np.abs(psi) ** 2
    count = rng.multinomial(samples, p / p.sum())
    live = count > 0
    local = np.zeros(len(words), complex)
    local[live] = (h @ psi)[live] / psi[live]
    share = count / samples
    energy = float((share * local).sum().real)
    f = share * (local - energy)
    return model.backward(x, 2 * f.real, 2 * f.imag)


def trajectories(spark: SparkSession, sf_dir: str, steps: int = 110, size: int = 2000, outer: int = 4) -> list[loop.RunResult]:
    """The two-word 84-orbital problem by the engine and by the hybrid baseline: generation, duplicate removal, top-K growth up to
    ``size`` configurations, remap and energies of each, ``steps`` optimizer steps in ``outer`` iterations."""
    ham = hamiltonian.table(spark, sf_dir, 84, 6, orbital="partkey", band=3, spacing=40)
    inner = [steps // outer - 1 + (i < steps % outer) for i in range(outer)]
    cfgs = [loop.LoopConfig(stages=replace(s, k=size), iterations=outer, lr=3e-3, max_size=size, inner=max(inner), window=outer) for s in (staging.ENGINE, staging.HYBRID)]
    return [loop.run(spark, ham, Rbm.start(84, 8), cfg) for cfg in cfgs]


def trajectory_pair(spark: SparkSession, sf_dir: str, steps: int = 110, size: int = 2000) -> DataFrame:
    """``steps, space, mae, rmse, max``: the engine's energy trajectory on the 84-orbital problem against the hybrid baseline's."""
    engine, hybrid = trajectories(spark, sf_dir, steps, size)
    frames = [spark.createDataFrame([(i, e) for i, e in enumerate(r.trajectory[:steps])], "iter int, energy double") for r in (engine, hybrid)]
    return metrics.trajectory_diff(*frames).select(F.lit(min(steps, len(engine.trajectory))).alias("steps"), F.lit(engine.space.count()).alias("space"), "mae", "rmse", "max")


def medium(spark: SparkSession, sf_dir: str, parts: int = 32) -> DataFrame:
    """The 64-orbital two-word set: ``sources, generated, unique, rate``, generated and made unique over the cluster, by sampled ranges on bitmaps."""
    spec, sources = configuration_set(spark, sf_dir, "emb64")
    sources = staged(sources, "sources")
    n = sources.count()
    unique = dense.range_unique(sources, spec, parts).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("unique"))
    generated = n * metrics.edge_bound(spec.m, spec.n)
    return unique.select(F.lit(n).cast("long").alias("sources"), F.lit(generated).cast("long").alias("generated"), "unique", (1 - F.col("unique") / F.lit(float(max(generated, 1)))).alias("rate"))


def breakdown(spark: SparkSession, sf_dir: str, parts: int = 8, problems: tuple[str, ...] = ("heavy", "many")) -> DataFrame:
    """``problem, variant, stage, seconds, share``: the ablation on a problem with many moves per source and one with many sources.

    ``heavy``: the 64-orbital embeddings, 25,143 moves a source before a banded Hamiltonian screens them; ``many``: the order
    baskets, 1,344 moves a source.
    """
    made = {"heavy": (lambda: hamiltonian.table(spark, sf_dir, 64, 6, orbital="partkey", band=3), "emb64"), "many": (lambda: hamiltonian.table(spark, sf_dir, 25, 4), "ord4")}
    out = []
    for name in problems:
        ham, setname = made[name][0](), made[name][1]
        _, sources = configuration_set(spark, sf_dir, setname)
        rows = loop.ablation(spark, staged(sources, "sources"), excite.tables(ham), Rbm.start(ham.spec.m, 16), replace(staging.ENGINE, parts=parts))
        out.append(rows.withColumn("problem", F.lit(name)))
    both = reduce(DataFrame.unionByName, out)
    total = both.groupBy("problem", "variant").agg(F.sum("seconds").alias("_t"))
    return both.join(total, ["problem", "variant"]).select("problem", "variant", "stage", "seconds", (F.col("seconds") / F.col("_t")).alias("share"), "energy")


def dedup_matrix(spark: SparkSession, sf_dir: str, widths: tuple[int, ...] = (32, 64), sources: tuple[str, ...] = SOURCES) -> DataFrame:
    """Per source and width: balance of the exchanged and of the unique rows, redundancy and throughput."""
    rows = []
    for name in sources:
        keys, n = keys_of(spark, sf_dir, name)
        for parts in widths:
            began = time.perf_counter()
            report = dedup.report(keys, parts)
            seconds = time.perf_counter() - began
            sent, left = (metrics.balance(report.parts, c).first() for c in ("exchanged", "unique"))
            rows.append((name, parts, n, report.exchanged, report.unique, sent["ratio"], sent["cv"], left["ratio"], left["cv"], report.samples, report.boundary_duplicates, metrics.throughput(n, seconds)))
    return spark.createDataFrame(rows, "source string, parts int, generated long, exchanged long, unique long, ratio double, cv double, unique_ratio double, unique_cv double, samples long, boundary int, millions_per_s double")


def dedup_skewed(spark: SparkSession, sf_dir: str, parts: int = 32, copies: int = 50) -> DataFrame:
    """Line keys with the most frequent parts repeated: balance of exchanged rows by ranges and by hash."""
    keys = line_keys(spark, sf_dir)
    hot = keys.where(F.col("w0") < (1 << 20) * 20).withColumn("_c", F.explode(F.sequence(F.lit(1), F.lit(copies)))).select("w0")
    skewed = staged(keys.unionByName(hot), "keys")
    report = dedup.report(skewed, parts)
    hashed = skewed.groupBy(F.pmod(F.hash("w0"), F.lit(parts)).alias("part")).agg(F.count("*").alias("exchanged"))
    both = metrics.balance(report.parts, "exchanged").withColumn("method", F.lit("ranges")).unionByName(metrics.balance(hashed, "exchanged").withColumn("method", F.lit("hash")))
    return both.select("method", "max", "min", "ratio", "cv")


def _iteration(made: DataFrame, sample: DataFrame, spec: ProblemSpec, parts: int) -> tuple[float, DataFrame]:
    """(seconds, amplitudes) of one iteration without energies: generation, duplicate removal by ranges, inference and top-K."""
    began = time.perf_counter()
    unique = dedup.range_presampled(made, sample, parts)
    amps = staged(infer.run(unique, Rbm.start(spec.m, 16), spec), "amps")
    topk.two_level(amps.withColumn("score", F.col("log_abs")), 100).collect()
    return time.perf_counter() - began, amps


def _thinned(sources: DataFrame, spec: ProblemSpec, n: int) -> DataFrame:
    """Sources whose moves set the splitters: about 200 of them, at least one in a thousand."""
    return sources.where(F.pmod(F.xxhash64(*spec.names), F.lit(1000)) < min(1000, 1 + 200_000 // max(n, 1)))


def strong_scaling(spark: SparkSession, sf_dir: str, widths: tuple[int, ...] = (2, 4, 8, 16, 32, 64)) -> DataFrame:
    """Fixed sources, more partitions: seconds of an iteration, efficiency, generated and unique keys, and balance of the unique keys.

    On one machine only the balance is meaningful beyond its cores.
    """
    spec, sources = configuration_set(spark, sf_dir, "ord4")
    sources = staged(sources, "sources")
    n = sources.count()
    rows = []
    for p in widths:
        seconds, amps = _iteration(generate.moves(sources.repartition(p), spec), generate.moves(_thinned(sources, spec, n), spec), spec, p)
        counts = spark.range(p).select(F.col("id").cast("int").alias("part")).join(amps.groupBy("part").count(), "part", "left").na.fill(0)
        rows.append((p, seconds, n * metrics.edge_bound(spec.m, spec.n), amps.count(), metrics.balance(counts, "count").first()["ratio"]))
    return metrics.scaling(spark.createDataFrame(rows, "p int, seconds double, generated long, unique long, ratio double"), "strong")


def block_of(spec: ProblemSpec, blocks: int):
    """Block of a source of one word, by a rule that SQL can write down too."""
    return F.pmod(F.col(spec.names[0]) * 7919 % 1009, F.lit(blocks)).cast("int")


def _blocks(spark: SparkSession, sf_dir: str, name: str, blocks: int) -> tuple[ProblemSpec, DataFrame]:
    spec, sources = configuration_set(spark, sf_dir, name)
    return spec, sources.withColumn("block", block_of(spec, blocks))


def weak_scaling(spark: SparkSession, sf_dir: str, name: str = "emb20", widths: tuple[int, ...] = (2, 4, 8, 16, 32, 64)) -> DataFrame:
    """Sources grow with the partitions: generated, unique, unique per partition (the effective load), seconds of an iteration, efficiency."""
    spec, sources = _blocks(spark, sf_dir, name, max(widths))
    sources = staged(sources, "sources")
    rows = []
    for p in widths:
        mine = sources.where(F.col("block") < p).drop("block")
        n = mine.count()
        seconds, amps = _iteration(generate.moves(mine.repartition(p), spec), generate.moves(_thinned(mine, spec, n), spec), spec, p)
        unique = amps.count()
        rows.append((p, seconds, n * metrics.edge_bound(spec.m, spec.n), unique, unique / p))
    return metrics.scaling(spark.createDataFrame(rows, "p int, seconds double, generated long, unique long, unique_per_p double"), "weak")


def weak_load(spark: SparkSession, sf_dir: str, name: str = "emb20", widths: tuple[int, ...] = (2, 4, 8, 16, 32, 64)) -> DataFrame:
    """``p, generated, unique``: the whole-number side of ``weak_scaling``, by the sampled ranges."""
    spec, sources = _blocks(spark, sf_dir, name, max(widths))
    frames = []
    for p in widths:
        keys = staged(generate.moves(sources.where(F.col("block") < p).drop("block"), spec), "keys")
        unique = dedup.range_sampled(keys, p).agg(F.count("*").alias("unique"))
        frames.append(unique.select(F.lit(p).alias("p"), F.lit(keys.count()).cast("long").alias("generated"), "unique"))
    return reduce(DataFrame.unionByName, frames)


def redundancy_growth(spark: SparkSession, sf_dir: str, name: str = "doc6", blocks: int = 16) -> DataFrame:
    """Generated against unique keys as blocks of sources are added; the curve is exact, from the block where a key is first seen."""
    spec, sources = configuration_set(spark, sf_dir, name)
    edges = generate.moves(sources, spec, source=True)
    block = F.pmod(F.col(spec.source_names[0]) * 7919 % 1009, F.lit(blocks)).cast("int")
    return metrics.growth_curve(edges.select(*spec.names, block.alias("block")))


def memory(spark: SparkSession, sf_dir: str, sweep: tuple[int, ...] = (4, 16), names: tuple[str, ...] = ("emb20", "ord4", "evt3", "doc6"), parts: int = 16) -> DataFrame:
    """``source, batches, sources, generated, unique, theoretical, in_core, staged, reduction``: bytes held at once without and with stages.

    Four key sources, moves only.  ``in_core``: all edges, unique keys and amplitudes of the run as the counts of a single pass
    have them.  ``staged``: from the run itself, in ``batches`` key-range batches of sources, the largest of what one step held:
    the edges of a batch that is written while the next is made, or the unique keys and amplitudes of a range, beside the
    model's weights.
    """
    rows = []
    for name in names:
        spec, sources = configuration_set(spark, sf_dir, name)
        sources = staged(sources.select(*spec.names), "sources")
        n, weights = sources.count(), 8 * Transformer.start(spec.m, spec.n).size()
        edge, key = 8 * spec.words * 2 + 8 + 4, 8 * spec.words + 4 + 16
        for batch in sweep:
            work = Workspace(spark)
            made = [work.staged(generate.moves(piece, spec, source=True), "edges") for piece in staging.batches(sources, -(-n // batch), n)]
            counts = [f.count() for f in made]
            unique = work.staged(dedup.range_sampled(reduce(DataFrame.unionByName, made).select(*spec.names), parts), "unique")
            largest, u = unique.groupBy("part").count().agg(F.max("count"), F.sum("count")).first()
            held = weights + max(2 * max(counts) * edge, (largest or 0) * key)
            generated = sum(counts)
            theoretical = metrics.theoretical_bytes(generated, u or 0, spec.words)
            rows.append((name, batch, n, generated, u or 0, theoretical, generated * (edge + 8) + (u or 0) * key, held, metrics.reduction(theoretical, held)))
            work.drop("edges", "unique")
    return spark.createDataFrame(rows, "source string, batches int, sources long, generated long, unique long, theoretical long, in_core long, staged long, reduction double")


def memory_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole-number side of ``memory`` for two sources in four batches."""
    return memory(spark, sf_dir, sweep=(4,), names=("emb20", "evt3")).select("source", "sources", "generated", "unique")


def table_footprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of the padded tables against the dense matrix, for the model and table problems, and the arithmetic of 14 in 56."""
    hams = [hamiltonian.two_level_molecule(), hamiltonian.lattice(4, 4), hamiltonian.lattice(6, 6), hamiltonian.table(spark, sf_dir, 12, 4)]
    frames = [excite.footprint(excite.tables(h), spark).withColumn("problem", F.lit(h.name)) for h in hams]
    one, two = metrics.virtual_size(14, 27, 354)
    from math import comb

    size = (one + two) * excite.ENTRY
    dense = 8.0 * float(comb(56, 14)) ** 2
    frames.append(spark.createDataFrame([(size, two * excite.ENTRY, dense, dense / size, "example_14_56")], "bytes long, pair_bytes long, dense_bytes double, ratio double, problem string"))
    return reduce(DataFrame.unionByName, frames)


def sampling_energy(spark: SparkSession, sf_dir: str, samples: int = 20_000) -> DataFrame:
    """The sampling baseline on the four-site ring: energy, error, distinct and total samples."""
    ham = hamiltonian.lattice(4, 4)
    model = Transformer.start(8, 4, width=16, layers=2, hidden=16)
    drawn = sampling.draw(spark, model, ham.spec, samples)
    return sampling.energy(drawn, model, excite.tables(ham))


def loop_history(spark: SparkSession, sf_dir: str, iterations: int = 3) -> DataFrame:
    """A few iterations of the whole loop on the table problem, with the published model: width 32, 4 layers of 4 heads, 4-layer phase."""
    ham = hamiltonian.table(spark, sf_dir, 12, 4, spacing=40)
    cfg = loop.LoopConfig(stages=replace(staging.ENGINE, parts=4, k=64, sources=32, slices=2), iterations=iterations)
    return loop.run(spark, ham, Transformer.start(12, 4, width=32, layers=4, heads=4), cfg).history.drop("seconds")


def loop_growth(spark: SparkSession, sf_dir: str, iterations: int = 3, k: int = 50) -> DataFrame:
    """The whole loop with whole-number amplitudes: sizes and energies of every iteration, which SQL can follow."""
    ham = hamiltonian.table(spark, sf_dir, 12, 4)
    cfg = loop.LoopConfig(stages=replace(staging.ENGINE, parts=4, k=k, sources=20, slices=2), iterations=iterations, window=iterations)
    out = loop.run(spark, ham, ClosedForm(), cfg).history
    return out.select("iter", "n_space", "n_generated", "n_unique", F.round("energy", 6).alias("energy"))


def stage_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured shares of the stages of an engine iteration and of the hybrid baseline's, and the speed-up of each stage and of all."""
    _, sources = configuration_set(spark, sf_dir, "emb12")
    t, model = excite.tables(hamiltonian.table(spark, sf_dir, 12, 4)), Rbm.start(12, 16)
    sources, frames = staged(sources, "sources"), {}
    for name, cfg in (("hybrid", staging.HYBRID), ("engine", staging.ENGINE)):
        timer = metrics.StageTimer()
        first = staging.stage1(sources, t, cfg, timer)
        amps, _ = staging.stage2(first.unique, model, t, cfg, timer, sources)
        staging.stage3(first, amps, sources, t, cfg, timer)
        frames[name] = spark.createDataFrame(timer.rows, "iter int, stage string, seconds double")
    shares = metrics.stage_share(frames["engine"]).select("stage", "seconds", "share")
    return metrics.speedup(frames["hybrid"], frames["engine"]).join(shares, "stage", "left")


def convergence(spark: SparkSession, sf_dir: str, steps: int = 1200) -> DataFrame:
    """First step under the threshold and the last smoothed slope of a whole run on the molecule."""
    ham = hamiltonian.two_level_molecule()
    t = excite.tables(ham)
    reference, _, words = exact.dense_ground(t)
    cfg = loop.LoopConfig(stages=replace(staging.ENGINE, parts=2, k=len(words)), iterations=2, lr=0.05, decay=0.0, inner=steps, window=2, cool=True)
    run = loop.run(spark, ham, Tabular.start(words), cfg)
    history = spark.createDataFrame(list(enumerate(run.trajectory)), "iter int, energy double")
    slope = metrics.smoothed(history).agg(F.max_by("slope", "iter").alias("slope"))
    return metrics.first_below(history, reference).join(slope)


def exact_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact lowest values of the table problems of four sizes, whose counts are made once."""
    counts = hamiltonian.pair_counts(spark, sf_dir, 12)
    hams = [hamiltonian.from_counts(counts, m, n) for m, n in ((8, 3), (10, 3), (12, 3), (12, 4))]
    return spark.createDataFrame([(h.name, exact.dense_ground(excite.tables(h))[0]) for h in hams], "problem string, energy double")
