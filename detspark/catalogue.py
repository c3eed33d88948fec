"""Queries on the given tables, and their DuckDB twins where SQL can express them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark import oracles as sql
from detspark import streaming, workloads
from detspark.functions import bits
from detspark.functions.ansatz import Rbm, Transformer, closed_form
from detspark.functions.schema import ProblemSpec
from detspark.operators import baseline, dedup, dense, energy, exact, excite, generate, infer, metrics, remap, space, topk
from detspark.operators.generate import ScreenPolicy
from detspark.plans.scratch import fresh_path, staged
from detspark.sources import hamiltonian
from detspark.sources.tables import brand_ranks, configuration_set, line_keys, load, stream_events

#: the problem that most exact checks use: orbitals, particles, parts, samples
M, N, PARTS, SAMPLES = 12, 4, 8, 64


def _problem(spark: SparkSession, sf_dir: str) -> tuple[excite.Tables, DataFrame]:
    """The whole-number table Hamiltonian and its selected space, the configurations of the embeddings."""
    _, sources = configuration_set(spark, sf_dir, "emb12")
    return excite.tables(hamiltonian.table(spark, sf_dir, M, N)), sources


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``l_orderkey, o``: the order and the orbital, the brand's rank, of each line."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    return lines.join(brand_ranks(load(spark, sf_dir, "part")), F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "o")


def _orbitals(spark: SparkSession, sf_dir: str) -> int:
    """Orbitals of the problem of the orders: one more than the highest that a line has."""
    return (_lines(spark, sf_dir).agg(F.max("o")).first()[0] or 0) + 1


def _packed(name: str):
    return lambda spark, sf_dir: configuration_set(spark, sf_dir, name)[1]


def _moves(spark: SparkSession, sf_dir: str, name: str = "ord3") -> DataFrame:
    """Redundant targets of a set, staged, as several strategies read them."""
    spec, sources = configuration_set(spark, sf_dir, name)
    return staged(generate.moves(sources, spec), "moves")


def _edges(form):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        t, sources = _problem(spark, sf_dir)
        return form(sources, t).select("sw0", "w0", F.col("h").cast("long").alias("h"), "kind")

    return query


def _screened(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    return generate.screen(generate.by_join(sources, t), t.spec, ScreenPolicy.fixed(10)).select("sw0", "w0", "h", "kind")


def _screened_scaled(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    amps = sources.withColumn("psi", closed_form([F.col("w0")]))
    return generate.screen(generate.by_join(sources, t), t.spec, ScreenPolicy.scaled(2000), amps).select("sw0", "w0", "h", "kind")


def _screened_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    edges = staged(generate.by_join(sources, t), "edges")
    kept = generate.screen(edges, t.spec, ScreenPolicy.budget(10_000), share=1.0)
    return kept.groupBy("kind").agg(F.count("*").alias("edges"), F.min(F.abs("h")).alias("smallest"))


def _single(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, _ = _problem(spark, sf_dir)
    total = F.aggregate("ctx", F.lit(0).cast("long"), lambda a, x: a + x)
    return t.single_frame(spark).select("p", "a", "h", total.alias("ctx"), F.col("flip_w0").alias("flip"), F.col("par_w0").alias("parity"))


def _double(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, _ = _problem(spark, sf_dir)
    return t.double_frame(spark).select("p", "q", "a", "b", "h", F.col("flip_w0").alias("flip"), F.col("par_w0").alias("parity"), "sgn0")


def _padded(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, _ = _problem(spark, sf_dir)
    _, two, _, _ = excite.padded(t, spark)
    real = F.size(F.filter("targets", lambda e: e["a"].isNotNull()))
    return two.select("p", "q", F.size("targets").alias("length"), real.alias("filled"))


def _distinct(method):
    """A method on the keys of the lines, most of which occur once: a copy that is lost or left shows."""
    return lambda spark, sf_dir: method(staged(line_keys(spark, sf_dir), "keys")).select("w0")


def _local(frame: DataFrame) -> DataFrame:
    """Local removal where all copies of a key are in one task: then what is left is distinct, and nothing else makes it so."""
    return dedup.local(frame.repartition(PARTS, "w0"))


def _cuts(spark: SparkSession, sf_dir: str):
    """Splitters by the sample that the engine uses, from tasks that hold the keys of one remainder each."""
    keys = line_keys(spark, sf_dir).repartitionById(8, F.pmod("w0", F.lit(8)).cast("int"))
    return dedup.splitters(dedup.regular_sample(keys, SAMPLES), PARTS)


def _splitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(i + 1, int(c[0])) for i, c in enumerate(_cuts(spark, sf_dir))], "j int, w0 long")


def _sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The regular sample itself, by groups of a column."""
    keys = line_keys(spark, sf_dir).withColumn("g", F.pmod("w0", F.lit(8)).cast("int"))
    return dedup.regular_sample_by(keys, "g", SAMPLES).select("g", "w0", F.round("weight", 9).alias("weight"))


def _balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    routed = dedup.route(line_keys(spark, sf_dir), _cuts(spark, sf_dir))
    counts = routed.groupBy("part").agg(F.count("*").alias("n"))
    return metrics.balance(counts, "n").select(*[F.round(c, 6).alias(c) for c in ("max", "min", "mean", "std", "ratio", "cv")])


def _two_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sampled ranges, on bitmaps, of the moves of the 64-orbital set, of which few repeat; keys of two words, summed up by the lower word's remainder."""
    spec, sources = configuration_set(spark, sf_dir, "emb64")
    unique = dense.keys(dense.range_unique(staged(sources, "sources"), spec, PARTS), spec)
    return unique.groupBy(F.pmod("w0", F.lit(97)).cast("int").alias("g")).agg(F.count("*").alias("unique"), F.sum(F.pmod("w0", F.lit(1_000_003))).alias("low"), F.sum("w1").alias("high"))


def _reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lowest fillings for the problem of the orders with as many particles as an order has brands, for each such number."""
    m = _orbitals(spark, sf_dir)
    held = _lines(spark, sf_dir).groupBy("l_orderkey").agg(F.size(F.collect_set("o")).alias("n"))
    sizes = sorted(r["n"] for r in held.select("n").distinct().collect())  # at most one for each orbital
    frames = [space.reference(spark, ProblemSpec(m, n)).select(F.lit(m).alias("m"), F.lit(n).alias("n"), "w0") for n in sizes]
    return reduce(DataFrame.unionByName, frames, spark.createDataFrame([], "m int, n int, w0 long"))


def _footprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, _ = _problem(spark, sf_dir)
    return excite.footprint(t, spark).select("bytes", "pair_bytes")


def _kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each kind of move generated on its own."""
    t, sources = _problem(spark, sf_dir)
    parts = [generate.by_join(sources, t, kinds=(k,)).select("sw0", "w0", "h", F.lit(k).alias("kind")) for k in (0, 1, 2)]
    return reduce(DataFrame.unionByName, parts)


def _reverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    edges = staged(generate.by_join(sources, t), "edges")
    unique = staged(dedup.range_sampled(edges.select("w0"), PARTS), "unique")
    indexed = remap.stored(edges, unique, t.spec)
    named = remap.with_uid(unique).select("uid", "w0")
    return indexed.groupBy("uid").agg(F.count("*").alias("sources"), F.min("sw0").alias("first"), F.max("sw0").alias("last")).join(named, "uid").select("w0", "sources", "first", "last")


def _amps(unique: DataFrame) -> DataFrame:
    return unique.withColumn("psi", closed_form([F.col("w0")]))


def _jit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges meet amplitudes through the ranges that the amplitudes lie in; numerators per source."""
    t, sources = _problem(spark, sf_dir)
    edges = staged(generate.by_join(sources, t), "edges")
    cuts = dedup.splitters(dedup.regular_sample(edges.select("w0"), SAMPLES), PARTS)
    amps = staged(_amps(dedup.compact(dedup.exchange(dedup.route(edges.select("w0"), cuts), PARTS))), "amps")
    joined = remap.jit(edges, amps, t.spec, cuts, PARTS)
    return joined.groupBy("sw0").agg(F.sum(F.col("h") * F.col("psi")).alias("num"))


def _closed(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    return _amps(sources)


def fixed_rbm(m: int = M, hidden: int = 3) -> Rbm:
    """Small weights by rule, so that SQL can write them down too."""
    import numpy as np

    i, h = np.arange(m), np.arange(hidden)
    return Rbm({"a": (i * 7 % 5 - 2) / 10, "b": (h - 1) / 5.0, "w": ((h[:, None] * 3 + i[None, :] * 5) % 7 - 3) / 10, "c": (i * 3 % 4 - 1) / 10})


def _rbm(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, sources = configuration_set(spark, sf_dir, "emb12")
    return sources.select("w0", F.round(fixed_rbm().column([F.col("w0")], M), 6).alias("log_abs"))


def _rbm_batched(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, sources = configuration_set(spark, sf_dir, "emb12")
    return infer.run(sources, fixed_rbm(), spec, batch=64).select("w0", F.round("log_abs", 6).alias("log_abs"))


def _transformer(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, sources = configuration_set(spark, sf_dir, "emb12")
    return infer.run(sources, Transformer.start(spec.m, spec.n), spec, batch=256)


def _scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    unique = dedup.range_native(generate.moves(sources, t.spec), PARTS)
    return unique.select("w0", F.abs(closed_form([F.col("w0")])).alias("score"))


def _running(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = staged(_scored(spark, sf_dir), "scored")
    return topk.running([scored.where(F.pmod("w0", F.lit(4)) == i) for i in range(4)], 50)


def _grown(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    base = sources.select("w0", F.lit(0).alias("iter_added"), F.lit(0).cast("long").alias("score"))
    fresh = _scored(spark, sf_dir).join(sources, "w0", "left_anti")
    return space.grow(base, topk.two_level(fresh, 50), t.spec, 1)


def _local_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    edges = staged(generate.by_join(sources, t), "edges")
    amps = _amps(dedup.range_native(edges.select("w0"), PARTS))
    rows = energy.local(edges, amps, t.spec)
    return rows.select("sw0", F.col("num_re").cast("long").alias("num"), F.col("psi_re").alias("psi"), F.round("eloc_re", 6).alias("eloc"))


def _total(form: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        t, sources = _problem(spark, sf_dir)
        edges = staged(generate.by_join(sources, t), "edges")
        amps = _amps(dedup.range_native(edges.select("w0"), PARTS))
        out = energy.energy(sources, t, amps, form, edges=edges)
        return out.select(F.col("num").cast("long").alias("num"), F.col("norm").cast("long").alias("norm"), F.round("energy", 6).alias("energy"), F.col("n").cast("long").alias("n"))

    return query


def _matvec(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, _ = _problem(spark, sf_dir)
    full = space.enumerate_space(spark, t.spec)
    vector = full.select("w0", closed_form([F.col("w0")]).alias("x"))
    return exact.matvec(generate.within(full, full, t), vector, t.spec).select("w0", F.col("x").cast("long").alias("x"))


def _curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, sources = configuration_set(spark, sf_dir, "ord3")
    edges = generate.moves(sources, spec, source=True).select("w0", F.pmod("sw0", F.lit(8)).cast("int").alias("block"))
    return metrics.growth_curve(edges)


def _redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, sources = configuration_set(spark, sf_dir, "ord3")
    return metrics.redundancy(generate.moves(sources, spec)).select(F.col("generated").cast("long").alias("generated"), F.col("unique").cast("long").alias("unique"), F.round("rate", 9).alias("rate"))


def _bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, sources = configuration_set(spark, sf_dir, "ord3")
    return sources.agg((F.count("*") * metrics.edge_bound(spec.m, spec.n)).alias("bound"))


def _hour() -> Column:
    """Hours since 1970 of an event."""
    return (F.datediff(F.to_date("ts"), F.lit("1970-01-01")) * 24 + F.hour("ts")).cast("int")


def _cents() -> Column:
    """Sum of the events' values in hundredths, so that it is the same in any order."""
    return F.sum(F.round(F.col("value") * 100).cast("long"))


def _peaks(spark: SparkSession, sf_dir: str, *kinds: str) -> DataFrame:
    """``iter, energy``: the largest value of the events of each hour, of some types or of all, as a history that falls."""
    events = load(spark, sf_dir, "events")
    mine = events.where(F.col("event_type").isin(*kinds)) if kinds else events
    return mine.groupBy(_hour().alias("iter")).agg((-F.max("value")).alias("energy"))


def _diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest views of each hour against the largest clicks."""
    out = metrics.trajectory_diff(_peaks(spark, sf_dir, "view"), _peaks(spark, sf_dir, "click"))
    return out.select(*[F.round(c, 6).alias(c) for c in out.columns])


def _share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shares of the event types in the values of each hour."""
    times = load(spark, sf_dir, "events").groupBy(_hour().alias("iter"), F.col("event_type").alias("stage")).agg(_cents().alias("seconds"))
    return metrics.stage_share(times).select("iter", "stage", F.round("share", 9).alias("share"))


def _speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Values of each event type up to the 15th of a month against those after it."""
    late = F.dayofmonth("ts") > 15
    times = load(spark, sf_dir, "events").groupBy(late.alias("late"), F.col("event_type").alias("stage")).agg(_cents().alias("seconds"))
    return metrics.speedup(times.where(~F.col("late")), times.where("late")).select("stage", F.round("speedup", 6).alias("speedup"))


def _efficiency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The values of the events of each hour of the day, taken as the seconds on so many workers."""
    times = load(spark, sf_dir, "events").groupBy((F.hour("ts") + 1).alias("p")).agg(_cents().alias("seconds"))
    modes = [metrics.scaling(times, m).withColumn("mode", F.lit(m)) for m in ("strong", "weak")]
    return reduce(DataFrame.unionByName, modes).select("mode", "p", F.round("efficiency", 9).alias("efficiency"))


def _converged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First hour whose largest event comes near the largest of all."""
    history = _peaks(spark, sf_dir)
    return metrics.first_below(history, history.agg(F.min("energy")).first()[0] or 0.0)


def _stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    from detspark.sources.tables import EVENTS

    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def _stream_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _stream(spark, sf_dir).select(F.col("event_id").alias("w0"), F.col("value").alias("score"))
    state, query = streaming.top(rows, 50, fresh_path(spark, "stream"))
    query.awaitTermination()
    return state.frame(spark)


def _stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    keys = streaming.dedup(_stream(spark, sf_dir).select((F.col("user_id") * 24 + F.hour("ts")).alias("w0")))
    out = fresh_path(spark, "stream-unique")
    query = keys.writeStream.format("parquet").option("path", out).option("checkpointLocation", fresh_path(spark, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema("w0 long").parquet(out)


def _windows(gap: str | None = None, slide: str | None = None):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        windows = streaming.window_configurations(load(spark, sf_dir, "events"), ProblemSpec(24, 3), slide=slide, gap=gap)
        return streaming.configurations(windows, ProblemSpec(24, 3))

    return query


def _allpairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, sources = _problem(spark, sf_dir)
    return baseline.couple_allpairs(sources, space.enumerate_space(spark, t.spec), t).select("sw0", "w0", "kind")


def iteration(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One iteration on the order baskets without a Hamiltonian: moves, range-wise duplicate removal, amplitudes, top-K and growth."""
    spec, sources = configuration_set(spark, sf_dir, "ord3")
    unique = dedup.range_native(generate.moves(sources, spec), PARTS)
    scored = unique.select("w0", F.abs(closed_form([F.col("w0")])).alias("score"))
    top = topk.exact(scored.join(sources, "w0", "left_anti"), 100)
    return space.grow(sources.select("w0", F.lit(0).alias("iter_added"), F.lit(0).cast("long").alias("score")), top, spec, 1)


QUERIES = {
    **{f"config_pack_{label}": _packed(name) for label, name in (("emb", "emb20"), ("emb64", "emb64"), ("orders", "ord3"), ("orders4", "ord4"), ("events", "evt3"), ("docs", "doc6"))},
    "space_enumerate": lambda spark, sf_dir: space.enumerate_space(spark, ProblemSpec(_orbitals(spark, sf_dir), N)),
    "excitation_single": _single, "excitation_double": _double, "excitation_padded": _padded,
    "couple_virtual": _edges(generate.virtual), "couple_join": _edges(generate.by_join), "couple_batch": _edges(generate.by_batch), "couple_rowwise": _edges(baseline.generate_rowwise),
    "couple_allpairs": _allpairs, "couple_screened": _screened, "couple_screened_scaled": _screened_scaled, "couple_screened_budget": _screened_budget,
    "dedup_local": _distinct(_local), "dedup_sample": _sampled, "dedup_two_words": _two_words,
    "dedup_range_sampled": _distinct(lambda f: dedup.range_sampled(f, PARTS)), "dedup_range_window": _distinct(lambda f: dedup.range_sampled(f, PARTS, levels=2, compact_how="window")),
    "dedup_range_rebalanced": _distinct(lambda f: dedup.range_sampled(f, PARTS, rebalance="unique")), "dedup_range_native": _distinct(lambda f: dedup.range_native(f, PARTS)),
    "dedup_hash": _distinct(baseline.dedup_hash), "dedup_salted": _distinct(lambda f: baseline.dedup_salted(f, PARTS)), "dedup_central": _distinct(lambda f: baseline.dedup_central(f, PARTS)),
    "dedup_splitters": _splitters, "dedup_balance": _balance,
    "reverse_index": _reverse, "remap_jit": _jit,
    "amplitude_closed_form": _closed, "amplitude_rbm": _rbm, "amplitude_rbm_batched": _rbm_batched, "transformer_infer": _transformer,
    "topk_exact": lambda s, d: topk.exact(_scored(s, d), 50), "topk_two_level": lambda s, d: topk.two_level(_scored(s, d), 50, batch=64), "topk_running": _running, "topk_large": lambda s, d: topk.large(_scored(s, d), 50, parts=8),
    "space_grow": _grown, "local_energy": _local_energy, "global_energy": _total("mixed"), "variational_energy": _total("variational"), "exact_power_step": _matvec,
    "redundancy_curve": _curve, "redundancy": _redundancy, "edge_bound": _bound, "trajectory_diff": _diff, "stage_share": _share, "stage_speedup": _speedup, "scaling_efficiency": _efficiency, "first_below": _converged,
    "stream_topk": _stream_topk, "stream_dedup": _stream_dedup, "window_day": _windows(), "window_sliding": _windows(slide="6 hours"), "window_session": _windows(gap="6 hours"),
    "iteration": iteration, "sampling_energy": workloads.sampling_energy, "loop_run": workloads.loop_history, "loop_growth": workloads.loop_growth, "couple_kinds": _kinds, "space_reference": _reference, "footprint_table": _footprint,
    "stage_measures": workloads.stage_measures, "convergence": workloads.convergence, "w7_load": workloads.weak_load, "w9_counts": workloads.memory_counts,
    "w1_accuracy": workloads.accuracy_small, "w2_trajectory": workloads.trajectory_pair, "w3_medium": workloads.medium, "w4_breakdown": workloads.breakdown,
    "w5_dedup_matrix": workloads.dedup_matrix, "w5_dedup_skewed": workloads.dedup_skewed, "w6_strong": workloads.strong_scaling, "w7_weak": workloads.weak_scaling, "w8_growth": workloads.redundancy_growth,
    "w9_memory": workloads.memory, "w10_footprint": workloads.table_footprint, "exact_values": workloads.exact_values,
}

ORACLES = sql.ORACLES
