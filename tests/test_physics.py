"""Bits, tables, generation, exact answers, models and gradients."""

from dataclasses import replace
from math import comb

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from detspark.functions import ansatz, bits
from detspark.functions.schema import ProblemSpec
from detspark.operators import baseline, energy, exact, excite, generate, infer, metrics, optimize, sampling, space
from detspark.operators.generate import ScreenPolicy
from detspark.plans import loop, staging
from detspark.sources import hamiltonian
from detspark.sources.tables import configuration_set


def test_worked_bit_string(spark):
    row = spark.createDataFrame([("01100010",)], "b string").select(*[w.alias("w0") for w in bits.parse(F.col("b"), 8)])
    got = row.select("w0", bits.popcount([F.col("w0")]).alias("n"), bits.show([F.col("w0")], 8).alias("s"), bits.occupied([F.col("w0")], 8).alias("o"), bits.virtual([F.col("w0")], 8).alias("v")).first()
    assert (got.w0, got.n, got.s, got.o, got.v) == (98, 3, "01100010", [1, 5, 6], [0, 2, 3, 4, 7])
    assert metrics.edge_bound(8, 3) == 15 + 30 == generate.moves(row, ProblemSpec(8, 3)).count()


@settings(max_examples=40, deadline=None)
@given(st.integers(2, 90), st.data())
def test_words_round_trip(m, data):
    orbitals = sorted(data.draw(st.sets(st.integers(0, m - 1))))
    words = np.array([bits.mask_words(orbitals, m)], np.int64)
    assert (words >= 0).all()
    x = bits.to_bits(words, m)
    assert np.flatnonzero(x[0]).tolist() == orbitals
    assert (bits.from_bits(x) == words).all()


def test_unranking_is_in_order():
    for m, n in ((6, 3), (9, 0), (5, 5), (70, 2)):
        words = space.unrank(np.arange(comb(m, n)), m, n)
        assert (np.bitwise_count(words).sum(1) == n).all()
        order = np.lexsort(words.T)
        assert (order == np.arange(len(words))).all() and len({tuple(w) for w in words.tolist()}) == comb(m, n)


def test_enumeration_forms_agree(spark):
    assert space.enumerate_space(spark, ProblemSpec(10, 3)).count() == comb(10, 3)
    wide = space.enumerate_space(spark, ProblemSpec(26, 2))
    assert wide.count() == comb(26, 2) == wide.distinct().count()
    assert space.enumerate_space(spark, ProblemSpec(8, 4), sector=(2, 2)).count() == comb(4, 2) ** 2
    with pytest.raises(Exception, match="wrong number of ones"):
        space.checked(spark.createDataFrame([(7,)], "w0 long"), ProblemSpec(4, 2)).count()


@pytest.mark.parametrize(("ham", "value"), [
    (hamiltonian.two_level_molecule(), -1.137269804), (hamiltonian.lattice(2, 2, ring=False), (4 - 32**0.5) / 2),
    (hamiltonian.lattice(4, 4), -2.102748483), (hamiltonian.lattice(4, 4, u=0.0), -4.0),
])
def test_known_energies(ham, value):
    t = excite.tables(ham)
    got, _, words = exact.dense_ground(t)
    assert abs(got - value) < 1e-8
    h = exact.dense_matrix(t, words)
    assert np.abs(h - h.T).max() < 1e-12


@pytest.mark.parametrize(("m", "n", "spacing", "value"), [(8, 3, 0, -312.511641821), (12, 4, 0, -585.913345950), (12, 4, 40, -23.973307)])
def test_table_energies(spark, sf, m, n, spacing, value):
    t = excite.tables(hamiltonian.table(spark, sf, m, n, spacing=spacing))
    assert abs(exact.dense_ground(t)[0] - value) < 2e-6


def test_lanczos_agrees(spark):
    t = excite.tables(hamiltonian.two_level_molecule())
    assert abs(exact.lanczos(t, exact.full_space(spark, t)) + 1.137269804) < 1e-8
    assert abs(exact.selected_ground(exact.full_space(spark, t), t) + 1.137269804) < 1e-8


def test_generation_forms_agree_on_two_words(spark, sf):
    ham = hamiltonian.table(spark, sf, 84, 6, orbital="partkey", band=1, spacing=40)
    t = excite.tables(ham)
    start = space.reference(spark, ham.spec)
    forms = [f(start, t) for f in (generate.by_join, generate.by_batch, generate.virtual, baseline.generate_rowwise)]
    rows = [sorted(map(tuple, f.select(*ham.spec.names, "h", "kind").collect())) for f in forms]
    assert rows[0] == rows[1] == rows[2] == rows[3] and len(rows[0]) > 10
    assert forms[0].where(sum(F.bit_count(w) for w in ham.spec.names) != 6).count() == 0


def test_generation_does_not_shuffle(spark, sf):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    plan = generate.by_join(spark.range(4).select((F.col("id") * 0 + 15).alias("w0")), t)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "BroadcastHashJoin" in plan


def test_screening(spark, sf):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    edges = generate.by_join(sources, t).cache()
    fixed = generate.screen(edges, spec, ScreenPolicy.fixed(10))
    assert fixed.where("kind = 0").count() == edges.where("kind = 0").count()
    assert fixed.where("kind > 0 and abs(h) <= 10").count() == 0
    assert generate.dropped_weight(edges, fixed).first()[0] == edges.where("kind > 0 and abs(h) <= 10").agg(F.sum(F.abs("h"))).first()[0]
    assert generate.screen(edges, spec, ScreenPolicy.budget(5000), share=1.0).where("kind > 0").count() <= 5000
    amps = sources.withColumn("psi", F.lit(2))
    assert generate.screen(edges, spec, ScreenPolicy.scaled(20), amps).count() == fixed.count()


def _models():
    words = exact.all_words(ProblemSpec(8, 4))
    return [ansatz.Tabular.start(words), ansatz.Rbm.start(8, 5), ansatz.Transformer.start(8, 4, width=8, layers=2, heads=2, hidden=6)]


@pytest.mark.parametrize("model", _models(), ids=lambda m: type(m).__name__)
def test_gradients_by_finite_differences(model):
    t = excite.tables(hamiltonian.lattice(4, 4))
    words = exact.all_words(t.spec)
    h = exact.dense_matrix(t, words)
    grads = optimize.dense_gradient(model, words, h, 8)
    for k, p in model.params.items():
        for i in list(np.ndindex(p.shape))[:4]:
            keep, values = p[i], []
            for d in (1e-5, -1e-5):
                p[i] = keep + d
                values.append(optimize.dense_energy(model, words, h, 8))
            p[i] = keep
            assert abs((values[0] - values[1]) / 2e-5 - grads[k][i]) < 1e-6


@pytest.mark.parametrize(("m", "n"), [(6, 2), (8, 4), (12, 3)])
def test_autoregressive_model_is_normalised(m, n):
    words = exact.all_words(ProblemSpec(m, n))
    log, _ = ansatz.Transformer.start(m, n).forward(bits.to_bits(words, m))
    assert abs(np.exp(2 * log).sum() - 1) < 1e-9


def test_distributed_gradient_and_energy_equal_dense(spark):
    ham = hamiltonian.lattice(4, 4)
    t, model = excite.tables(ham), ansatz.Transformer.start(8, 4, width=8, layers=1, heads=2, hidden=6)
    words = exact.all_words(ham.spec)
    h = exact.dense_matrix(t, words)
    full = space.enumerate_space(spark, ham.spec)
    local = energy.local(generate.by_join(full, t), energy.complex_amps(infer.run(full, model, ham.spec, batch=16)), ham.spec).cache()
    total = energy.total(local).first()
    assert abs(total["energy"] - optimize.dense_energy(model, words, h, 8)) < 1e-10
    assert total["energy"] >= exact.dense_ground(t)[0]
    got, want = optimize.gradient(local, total["energy"], total["norm"], model, ham.spec, 4), optimize.dense_gradient(model, words, h, 8)
    assert max(np.abs(got[k] - want[k]).max() for k in want) < 1e-10


def test_adamw_first_step():
    out = optimize.AdamW(lr=0.1, decay=0.5).step({"x": np.array([2.0])}, {"x": np.array([4.0])})
    assert abs(out["x"][0] - (2.0 * (1 - 0.05) - 0.1)) < 1e-7


def test_parameters_round_trip(spark):
    params = ansatz.Rbm.start(4, 2).params
    back = ansatz.restore(ansatz.save(params, spark, 3))
    assert all((back[k] == params[k]).all() for k in params)


def test_sampling_follows_the_model(spark):
    model = ansatz.Transformer.start(6, 2, width=8, layers=1, heads=2, hidden=4)
    drawn = sampling.draw(spark, model, ProblemSpec(6, 2), 20_000, chunks=3, levels=2)
    words = exact.all_words(ProblemSpec(6, 2))
    p = dict(zip(words[:, 0].tolist(), np.exp(2 * model.forward(bits.to_bits(words, 6))[0]).tolist(), strict=True))
    rows = {r["w0"]: r["count"] for r in drawn.collect()}
    assert sum(rows.values()) == 20_000 and set(rows) <= set(p)
    assert max(abs(rows.get(k, 0) / 20_000 - v) for k, v in p.items()) < 0.02
    assert rows == {r["w0"]: r["count"] for r in sampling.draw(spark, model, ProblemSpec(6, 2), 20_000, chunks=3, levels=2).collect()}


def test_training_reaches_the_exact_answer():
    t = excite.tables(hamiltonian.two_level_molecule())
    reference, _, words = exact.dense_ground(t)
    history = loop.dense_history(ansatz.Tabular.start(words), words, exact.dense_matrix(t, words), 4, 400, lr=0.05)
    assert abs(history[-1] - reference) < 1.6e-3


@pytest.mark.parametrize("ham", [hamiltonian.two_level_molecule(), hamiltonian.lattice(2, 2, ring=False)], ids=lambda h: h.name)
def test_the_loop_reaches_the_exact_answer_by_either_strategy(spark, ham):
    t = excite.tables(ham)
    reference, _, words = exact.dense_ground(t)
    runs = []
    for stages in (staging.ENGINE, staging.HYBRID):
        cfg = loop.LoopConfig(stages=replace(stages, parts=2, k=len(words), sources=2, slices=2), iterations=3, lr=0.05, decay=0.0, inner=1200, window=3, cool=True)
        runs.append(loop.run(spark, ham, ansatz.Tabular.start(words), cfg))
    engine, hybrid = (r.trajectory for r in runs)
    assert abs(engine[-1] - reference) < 1.6e-3 and abs(hybrid[-1] - reference) < 1.6e-3
    # rows lie in other orders, so long runs drift apart by rounding
    assert np.allclose(engine[:1300], hybrid[:1300], atol=1e-6) and min(engine) >= reference - 1e-9
    assert abs(runs[0].energies[2] - engine[2402]) < 1e-9


def test_growing_never_raises_the_selected_minimum(spark, sf):
    t = excite.tables(hamiltonian.table(spark, sf, 8, 3))
    full = space.enumerate_space(spark, t.spec).orderBy("w0")
    values = [exact.selected_ground(full.limit(k), t) for k in (5, 20, 56)]
    assert values[0] >= values[1] >= values[2] - 1e-9 and abs(values[2] + 312.511641821) < 1e-6


def test_footprint_example():
    assert metrics.virtual_size(14, 27, 354) == (378, 32_214) and 32_214 * excite.ENTRY < 400_000


def test_strategies_give_one_energy(spark, sf):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    rows = loop.ablation(spark, sources.orderBy("w0").limit(20), t, ansatz.Rbm.start(12, 4)).collect()
    values = [r["energy"] for r in rows]
    assert max(values) - min(values) < 1e-9 * abs(values[0]) and {r["variant"] for r in rows} == {"hybrid", "+generation", "+dedup"}


def test_ablation_deals_its_sources_out(spark, sf, monkeypatch):
    """A small set lies in one file, and generation follows its partitions: it must not run in one task."""
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    sources = configuration_set(spark, sf, "emb12")[1].coalesce(1)
    seen, first = [], loop.stage1
    monkeypatch.setattr(loop, "stage1", lambda space, *a, **b: seen.append(space.rdd.getNumPartitions()) or first(space, *a, **b))
    assert loop.ablation(spark, sources, t, ansatz.Rbm.start(12, 4), replace(staging.ENGINE, parts=5)).count() == 12
    assert len(seen) == 3 and min(seen) >= 5


def test_rowwise_on_two_words(spark, sf):
    """The row-wise loop and the batches give the same edges, with a frame for every few sources."""
    t = excite.tables(hamiltonian.table(spark, sf, 64, 3, orbital="partkey", band=3))
    frame = spark.createDataFrame([tuple(bits.mask_words(o, 64)) for o in ([0, 5, 63], [1, 62, 63], [10, 11, 12])], "w0 long, w1 long")
    rowwise = sorted(map(tuple, baseline.generate_rowwise(frame, t).collect()))
    assert rowwise and rowwise == sorted(map(tuple, generate.by_batch(frame, t).collect()))
