"""Duplicate removal, top-K, remap, measures, staging, streaming and the SQL surface."""

from math import comb

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from detspark import streaming
from detspark.functions import bits, sqlsurface
from detspark.functions.schema import ProblemSpec, space_schema
from detspark.operators import baseline, dedup, dense, energy, excite, generate, metrics, remap, space, topk
from detspark.plans import staging
from detspark.plans.scratch import staged
from detspark.sources import hamiltonian
from detspark.sources.tables import EVENTS, configuration_set, line_keys, read_bitstrings, read_integrals, write_sorted

TWO = [(5, 0), (5, 1), (3, 1), (5, 1), (0, 7), (5, 0), ((1 << 62) + 1, 2), ((1 << 62) + 1, 2)]


@pytest.mark.parametrize("rows", [[], [(7,)] * 50, [(i,) for i in range(40)], [((1 << 62) + i % 3,) for i in range(30)]], ids=["empty", "equal", "distinct", "high"])
@pytest.mark.parametrize("parts", [1, 3, 64])
def test_range_dedup_edges(spark, rows, parts):
    frame = spark.createDataFrame(rows, "w0 long")
    want = sorted({r[0] for r in rows})
    for how in ("adjacent", "window", "agg"):
        got = dedup.range_sampled(frame, parts, 4, compact_how=how, local_first=False)
        assert sorted(r["w0"] for r in got.collect()) == want


def test_two_word_keys(spark):
    frame = spark.createDataFrame(TWO, "w0 long, w1 long")
    for out in (dedup.range_sampled(frame, 3, 2), dedup.range_native(frame, 3), baseline.dedup_hash(frame), baseline.dedup_salted(frame, 2), baseline.dedup_central(frame, 2), dedup.range_sampled(frame, 2, 4, rebalance="unique"), dedup.range_presampled(frame, frame.limit(3), 3)):
        assert sorted((r["w0"], r["w1"]) for r in out.collect()) == sorted(set(TWO))
    copies = dedup.compact(dedup.exchange(dedup.route(frame, np.array([[5, 1]])), 2), multiplicity=True)
    assert sorted(r["copies"] for r in copies.collect()) == [1, 1, 2, 2, 2]


@settings(max_examples=50, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 5), st.integers(0, 5)), max_size=30), st.lists(st.tuples(st.integers(0, 5), st.integers(0, 5)), max_size=6))
def test_place_counts_splitters(keys, cuts):
    cuts = sorted(cuts, key=lambda c: c[::-1])
    got = dedup.place(np.array(keys, np.int64).reshape(-1, 2), np.array(cuts, np.int64).reshape(-1, 2)) if cuts else np.zeros(len(keys))
    assert got.tolist() == [sum(c[::-1] <= k[::-1] for c in cuts) for k in keys]


def test_routes_agree(spark, sf):
    keys = line_keys(spark, sf)
    cuts = dedup.splitters(dedup.regular_sample(keys, 32), 5)
    counts = [dedup.route(keys, cuts, how).groupBy("part").count().orderBy("part").collect() for how in ("tree", "search", "join", "asof")]
    assert all(c == counts[0] for c in counts)
    assert len(dedup.splitters(dedup.regular_sample(keys, 32), 5, levels=2)) == 4
    assert len(dedup.splitters_sketch(keys, 5)) == 4


def test_tree_and_search_agree_on_two_words(spark):
    rng = np.random.default_rng(3)
    rows = [tuple(map(int, r)) for r in rng.integers(0, 9, (400, 2))]
    cuts = np.array(sorted({tuple(map(int, r)) for r in rng.integers(0, 9, (20, 2))}, key=lambda r: r[::-1]), np.int64)
    frame = spark.createDataFrame(rows, "w0 long, w1 long")
    assert sorted(map(tuple, dedup.route(frame, cuts).collect())) == sorted(map(tuple, dedup.route(frame, cuts, "search").collect()))


def test_local_removal_and_the_sample_it_leaves(spark, sf):
    """Runs are distinct and sorted, hold every key, and are sampled at the places that the rule names."""
    keys = line_keys(spark, sf).repartition(3)
    runs = dedup.sorted_runs(keys, distinct=True)
    held = {}
    for r in runs.select("w0", F.col("_metadata.file_path").alias("f"), F.col("_metadata.row_index").alias("r")).collect():
        held.setdefault(r.f, []).append((r.r, r.w0))
    lists = [[w for _, w in sorted(v)] for v in held.values()]
    assert len(lists) == 3 and all(x == sorted(set(x)) for x in lists)
    assert set().union(*lists) == {r.w0 for r in keys.collect()}
    s = 10
    want = sorted((x[k * len(x) // s], len(x) / s) for x in lists for k in range(s))
    assert sorted((r.w0, r.weight) for r in dedup.sample_runs(runs, s).collect()) == want


def test_local_removal_of_a_large_task(spark):
    """Copies more than a million rows apart in one task go too."""
    keys = spark.range(0, 1_200_000, numPartitions=1).select(F.col("id").alias("w0"))
    once = dedup.local(keys.unionByName(keys).coalesce(1))
    assert once.agg(F.count("*"), F.countDistinct("w0")).first() == (1_200_000, 1_200_000)


def test_a_large_excitation_table_is_shuffled(spark, sf, monkeypatch):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    plain = sorted(map(tuple, generate.by_join(sources, t).collect()))
    monkeypatch.setattr(generate, "BROADCAST", 10)
    assert sorted(map(tuple, generate.by_join(sources, t).collect())) == plain


def test_balance_bound(spark, sf):
    keys = line_keys(spark, sf).repartition(8)
    parts, s = 8, 64
    report = dedup.report(keys, parts, s)
    n = report.exchanged
    assert report.parts.agg(F.max("exchanged")).first()[0] <= n / parts + n / s + parts
    assert report.boundary_duplicates == 0 and report.samples <= 8 * s
    assert report.generated - report.locally_removed == n >= report.unique
    again = dedup.rebalanced(dedup.range_sampled(keys, parts), parts).groupBy("part").count().agg(F.max("count"), F.min("count")).first()
    assert again[0] - again[1] <= 1


def test_one_exchange(spark, sf):
    frame = dedup.compact(dedup.exchange(dedup.route(line_keys(spark, sf), np.array([[1000], [2000]])), 3), "window")
    plan = frame._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "shufflepartitionidpassthrough" in plan
    native = dedup.range_native(line_keys(spark, sf), 4)._jdf.queryExecution().executedPlan().toString()
    assert native.count("Exchange") == 1


def test_central_refuses(spark, sf):
    with pytest.raises(ValueError, match="root"):
        baseline.dedup_central(line_keys(spark, sf), 2, limit=10)


@pytest.mark.parametrize("k", [0, 1, 5, 1000])
def test_topk_forms(spark, k):
    frame = spark.createDataFrame([(i, float(i % 7)) for i in range(60)], "w0 long, score double").repartition(5)
    want = sorted(((i, float(i % 7)) for i in range(60)), key=lambda r: (-r[1], r[0]))[:k]
    forms = [topk.exact(frame, k), topk.two_level(frame, k, batch=3), topk.large(frame, k, parts=4)]
    if k:
        forms += [topk.running([frame.where(F.col("w0") % 3 == i) for i in range(3)], k, prune=p) for p in (True, False)]
    for form in forms:
        assert sorted(map(tuple, form.collect())) == sorted(want)
    assert "TakeOrderedAndProject" in topk.exact(frame, 5)._jdf.queryExecution().executedPlan().toString()


def test_growth_and_size(spark):
    base = spark.createDataFrame([(3, 0, 1.0), (5, 0, 0.1)], "w0 long, iter_added int, score double")
    top = spark.createDataFrame([(5, 9.0), (6, 8.0), (9, 0.5)], "w0 long, score double")
    from detspark.functions.schema import ProblemSpec

    spec = ProblemSpec(4, 2)
    assert sorted(r["w0"] for r in space.grow(base, top, spec, 1).collect()) == [3, 5, 6, 9]
    assert sorted(r["w0"] for r in space.grow(base, top, spec, 1, max_size=3).collect()) == [3, 5, 6]
    assert sorted(r["w0"] for r in space.grow(base, top, spec, 1, max_size=2, replace=True).collect()) == [3, 6]


def test_remap_without_shuffling_amplitudes_again(spark, sf):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    edges = staged(generate.by_join(sources, t))
    cuts = dedup.splitters(dedup.regular_sample(edges.select("w0"), 64), 4)
    amps = staged(dedup.compact(dedup.exchange(dedup.route(edges.select("w0"), cuts), 4)).withColumn("psi", F.lit(1).cast("long")))
    joined = remap.jit(edges, amps, spec, cuts, 4)
    assert joined.count() == edges.count() == remap.jit(edges, amps, spec).count()
    assert "Exchange hashpartitioning(w0" not in joined._jdf.queryExecution().executedPlan().toString()
    assert sum(b.count() for b in remap.jit_batches(edges, amps, spec, 3)) == edges.count()
    uid = remap.with_uid(amps)
    assert remap.by_uid(remap.stored(edges, amps, spec), uid.select("uid", "psi")).count() == edges.count()
    assert remap.slice_broadcast(edges, amps, spec, 0).count() > 0


def test_exact_sums_do_not_depend_on_order(spark, sf):
    spec, sources = configuration_set(spark, sf, "emb12")
    t = excite.tables(hamiltonian.table(spark, sf, 12, 4))
    full = space.enumerate_space(spark, spec).withColumn("psi", (F.col("w0") * 7919 % 1009 - 504).cast("long"))
    values = {tuple(energy.energy(sources.repartition(p), t, full, eps=0.0).select("num", "norm").first()) for p in (1, 3, 7)}
    assert len(values) == 1


def test_batches_cover_everything_once(spark, sf, tmp_path):
    spec, sources = configuration_set(spark, sf, "emb12")
    write_sorted(sources, str(tmp_path / "space"), spec, partitions=3)
    table = spark.read.parquet(str(tmp_path / "space"))
    parts = [set(r["w0"] for r in b.collect()) for b in staging.batches(table, 100)]
    assert sum(map(len, parts)) == table.count() == len(set().union(*parts)) and max(map(len, parts)) < 160
    assert "PushedFilters: [IsNotNull(w0)" in list(staging.batches(table, 100))[1]._jdf.queryExecution().executedPlan().toString()
    assert staging.overlap([lambda i=i: i * i for i in range(5)]) == [0, 1, 4, 9, 16]
    assert staging.batch_bytes(table, 100) == 800


def test_measures(spark):
    counts = spark.createDataFrame([(0, 10), (1, 20), (2, 30)], "part int, n long")
    b = metrics.balance(counts, "n").first()
    assert b["ratio"] == 3.0 and abs(b["cv"] - np.std([10, 20, 30]) / 20) < 1e-12
    empty = metrics.balance(spark.createDataFrame([(0, 0), (1, 2)], "part int, n long"), "n").first()
    assert empty["ratio"] is None
    assert metrics.throughput(2_000_000, 1.0) == 2.0 and metrics.reduction(70, 37.5) == pytest.approx(0.464, abs=1e-3)
    timer = metrics.StageTimer()
    with timer.stage(0, "dedup"):
        pass
    assert timer.frame(spark).first()["share"] == 1.0


def test_sources(spark, tmp_path):
    from detspark.functions.schema import ProblemSpec

    spec = ProblemSpec(8, 3)
    spark.createDataFrame([("01100010",), ("00000111",)], "bits string").coalesce(1).write.option("header", True).csv(str(tmp_path / "c"))
    spark.createDataFrame([("01100010",), ("00000111",)], "bits string").coalesce(1).write.json(str(tmp_path / "j"))
    spark.createDataFrame([("01100010",), ("00000111",)], "bits string").coalesce(1).write.orc(str(tmp_path / "o"))
    for fmt, d in (("csv", "c"), ("json", "j"), ("orc", "o")):
        assert sorted(r["w0"] for r in read_bitstrings(spark, str(tmp_path / d), spec, fmt).collect()) == [7, 98]
    text = "&HEAD\n 0.674493 1 1 1 1\n0.181287D0 1 2 1 2\n0.697397 2 2 2 2\n0.663472 1 1 2 2\n-1.252477 1 1 0 0\n-0.475934 2 2 0 0\n0.7137758743754461 0 0 0 0\n"
    (tmp_path / "ints").write_text(text)
    ham = hamiltonian.from_integrals(read_integrals(spark, str(tmp_path / "ints")), ProblemSpec(4, 2))
    from detspark.operators import exact

    assert abs(exact.dense_ground(excite.tables(ham))[0] + 1.137269804) < 1e-8


def _stream_dir(spark, sf, path, late=False):
    events = spark.read.parquet(f"{sf}/events.parquet")
    slot = F.col("event_id") % 5
    slot = F.when(F.col("event_id") % 20 == 0, F.pmod(slot + 2, F.lit(5))).otherwise(slot) if late else slot
    for i in range(5):
        events.where(slot == i).coalesce(1).write.mode("append").parquet(str(path))
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(str(path))


def test_streams_equal_batch(spark, sf, tmp_path):
    stream = _stream_dir(spark, sf, tmp_path / "in", late=True)
    batch = spark.read.parquet(str(tmp_path / "in"))
    rows = lambda f: f.select(F.col("event_id").alias("w0"), F.col("value").alias("score"))
    state, query = streaming.top(rows(stream), 20, str(tmp_path / "ck1"))
    query.awaitTermination()
    assert sorted(map(tuple, state.frame(spark).collect())) == sorted(map(tuple, topk.exact(rows(batch), 20).collect()))
    seen = []
    query = streaming.redundancy_per_batch(stream.select((F.col("user_id")).alias("w0")), lambda i, n, u: seen.append((i, n, u)), str(tmp_path / "ck2"))
    query.awaitTermination()
    assert len(seen) == 5 and sum(n for _, n, _ in seen) == batch.count() and sum(u for *_, u in seen) == batch.select("user_id").distinct().count()
    unique = streaming.dedup(stream.select(F.col("user_id").alias("w0"), "ts"), "ts", "40 days")
    query = unique.writeStream.format("memory").queryName("u").outputMode("append").option("checkpointLocation", str(tmp_path / "ck3")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert spark.table("u").count() == batch.select("user_id").distinct().count()


def test_restart_goes_on(spark, sf, tmp_path):
    stream = _stream_dir(spark, sf, tmp_path / "in")
    out, ck = str(tmp_path / "out"), str(tmp_path / "ck")
    for _ in range(2):
        keys = streaming.dedup(stream.select(F.col("user_id").alias("w0")))
        keys.writeStream.format("parquet").option("path", out).option("checkpointLocation", ck).trigger(availableNow=True).start().awaitTermination()
        assert spark.read.parquet(out).count() == spark.read.parquet(out).distinct().count()


def test_top_k_of_a_restarted_stream(spark, sf, tmp_path):
    """Files that come between two runs of a query: the second goes on from the set of the first."""
    events = spark.read.parquet(f"{sf}/events.parquet").select(F.col("event_id").alias("w0"), F.col("value").alias("score"))
    place, ck = str(tmp_path / "in"), str(tmp_path / "ck")
    for low in (True, False):
        events.where((F.col("w0") % 2 == 0) == low).coalesce(1).write.mode("append").parquet(place)
        state, query = streaming.top(spark.readStream.schema(events.schema).parquet(place), 15, ck)
        query.awaitTermination()
    assert sorted(map(tuple, state.frame(spark).collect())) == sorted(map(tuple, topk.exact(events, 15).collect()))


def test_interval_join(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    got = streaming.nearby_pairs(events, events)
    assert got.where("b_ts <= a_ts or a_user <> b_user").count() == 0


def test_sql_surface(spark, sf):
    t = excite.tables(hamiltonian.two_level_molecule())
    sqlsurface.register(spark, t)
    sqlsurface.table_views(spark, t)
    sqlsurface.views(spark, t.spec, space=space.reference(spark, t.spec))
    rows = spark.sql("select c.w0, c.h, c.kind, config_show(c.w0) as b from space, lateral couple(space.w0) c").collect()
    assert {(r["b"], r["kind"]) for r in rows} >= {("0011", 0), ("1100", 2)}
    assert spark.sql("select config_parse('0110') as w").first()["w"] == 6
    assert spark.sql("select count(*) from t_double").first()[0] == len(t.double["p"])


def test_moves_on_bitmaps(spark):
    """Ranks are those of the moves one by one, copies included; what is left is the distinct moves; no run is larger than the space."""
    rng = np.random.default_rng(5)
    for m, n in ((64, 4), (12, 4), (5, 5), (6, 1), (7, 0), (5, 4)):
        spec = ProblemSpec(m, n)
        occupied = {tuple(sorted(map(int, rng.permutation(m)[:n]))) for _ in range(30)}
        words = np.array([bits.mask_words(list(o), m) for o in occupied], np.int64)
        every = np.arange(min(comb(m, n), 5000))
        assert dense.rank(space.unrank(every, m, n), spec).tolist() == every.tolist()
        ranks = np.concatenate([np.zeros(0, np.int64), *dense.moved_ranks(words, spec)])
        assert len(ranks) == len(words) * metrics.edge_bound(m, n)
        if m not in (64, 5):
            continue
        sources = spark.createDataFrame([tuple(map(int, w)) for w in words], space_schema(spec))
        made = sorted(map(tuple, generate.moves(sources, spec).collect()))
        assert sorted(map(tuple, space.unrank(ranks, m, n).tolist())) == made
        unique = dense.range_unique(sources, spec, 5, 16)
        got = dense.keys(unique, spec).collect()
        assert sorted(tuple(r)[:-1] for r in got) == sorted(set(made))
        assert unique.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0] == len(set(made))
        edges = sorted((min(k), max(k)) for p in {r.part for r in got} for k in [[tuple(r)[-2::-1] for r in got if r.part == p]])
        assert all(a[1] < b[0] for a, b in zip(edges, edges[1:], strict=False))  # parts are key ranges
    spec = ProblemSpec(12, 4)
    full = space.enumerate_space(spark, spec)
    pieces = dense.runs(full.unionByName(full).repartition(3), spec)
    assert pieces.count() == 3 and pieces.agg(F.max("n")).first()[0] <= comb(12, 4)
    with pytest.raises(ValueError, match="configurations"):
        dense.range_unique(full, ProblemSpec(84, 6), 2)
