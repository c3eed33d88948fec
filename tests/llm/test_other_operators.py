"""WARC, embeddings, sharding, packing, mixing and the pipeline."""

import base64
import hashlib
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from detspark.llm import lines, mixture, multiindex, packing, shards, simhash, topk, warc
from detspark.llm.catalogue import QUERIES
from detspark.llm.graph import forest
from detspark.plans.scratch import fresh_path

REC = "WARC/1.0\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:999>\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
PAGES = [(1, "u", "x" + REC * 2 + "tail"), (2, "u", REC), (3, None, None), (4, "a", "WARC/1.0\r\n"), (5, "b", "WARC/1.0\r\nWARC/1.0\r\n"), (6, "u", REC), (7, "é\r\nX: y", "é\r\n\r\nü" * 5000), (8, "u", ""), (9, "z", "WARC/1.0\r\nContent-Length: 99999\r\n\r\n")]


def digest(text):
    return base64.b32encode(hashlib.sha1((text or "").encode()).digest()).decode()


@pytest.mark.parametrize("compression", ["none", "gzip"])
@pytest.mark.parametrize("width", [64, 300, 1 << 26])
def test_marks_in_payloads_are_not_records(spark, width, compression):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").withColumn("kind", F.lit(1))
    path = fresh_path(spark, "warc")
    warc.write(pages.repartition(2), path, compression=compression)
    got = sorted((r.name, r.kind, r.payload_bytes, r.payload_digest) for r in warc.resolved(warc.read(spark, path, width)).collect())
    revisits = {2, 3}
    assert got == sorted((f"<urn:page:{i}>", "revisit" if i in revisits else "response", len((h or "").encode()), digest(h)) for i, _, h in PAGES)


def test_records_survive_other_splits_in_the_second_scan(spark, monkeypatch):
    """Cores may come or go between the two scans of an archive, which cuts it differently."""
    rows = [(i, "u", f"{i} " * 300 + REC * (1 + i % 3) + f"end of {i % 7}") for i in range(60)]
    path = fresh_path(spark, "warc")
    warc.write(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(6), path)
    plain, calls = warc._pieces, []

    def cut_anew(session, where):
        calls.append(where)
        for name, value in (("minPartitionNum", "1" if len(calls) == 1 else "40"), ("openCostInBytes", "1")):
            session.conf.set(f"spark.sql.files.{name}", value)
        return plain(session, where)

    monkeypatch.setattr(warc, "_pieces", cut_anew)
    try:
        got = sorted((r.name, r.payload_digest) for r in warc.read(spark, path).collect())
    finally:
        for name in ("minPartitionNum", "openCostInBytes"):
            spark.conf.unset(f"spark.sql.files.{name}")
    assert len(calls) == 2 and got == sorted((f"<urn:page:{i}>", digest(h)) for i, _, h in rows)


def test_warc_query_round_trip(spark, table_dir):
    rows = [*PAGES, (10, "q", "same"), (11, "q", "same"), (12, "q", "same")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: (r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in QUERIES["op2_warc"](spark, table_dir(pages=pages)).collect()}
    last = {}
    for i, _, h in rows:
        last[h or ""] = i
    assert got == {i: (len((h or "").encode()), digest(h), *(("response", None) if last[h or ""] == i else ("revisit", last[h or ""]))) for i, _, h in rows}
    assert QUERIES["op2_warc"](spark, table_dir(pages=pages.limit(0))).count() == 0
    odd = spark.createDataFrame([(1, "u", "same"), (1, "u", "same"), (None, "u", "x" + REC), (None, None, "x" + REC), (2, "u", "x" + REC)], "page_id long, url string, html string")
    back = sorted(((r.page_id, r.payload_digest, r.record_type, r.refers_to) for r in QUERIES["op2_warc"](spark, table_dir(pages=odd)).collect()), key=str)
    twice = digest("x" + REC)
    assert back == sorted([(1, digest("same"), "response", None)] * 2 + [(None, twice, "revisit", 2)] * 2 + [(2, twice, "response", None)], key=str)


def test_small_payloads_are_all_responses(spark):
    pages = spark.createDataFrame([(1, "u", "ab"), (2, "u", "ab"), (3, "u", "abcd"), (4, "u", "abcd")], "page_id long, url string, html string")
    assert {r.page_id: r._refers for r in warc.decided(pages, least=3).collect()} == {1: None, 2: None, 3: 4, 4: None}


def vectors(spark, n=600, seed=0):
    rng = np.random.default_rng(seed)
    centre = rng.normal(size=(12, 16))
    x = centre[rng.integers(12, size=n)] + rng.normal(0, 0.6, (n, 16))
    x[50:90] = x[49]
    for i in range(100, 260):
        x[i] = x[i - 60] + rng.normal(0, 0.08, 16)
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x.astype(np.float32))]
    odd = [(n, None), (n + 1, [0.0] * 16), (n + 2, [None] * 16), (n + 3, [float("nan")] * 16), (n + 4, [float("inf")] + [1.0] * 15), (n + 5, [1.0, 2.0]), (n + 6, [])]
    return x.astype(np.float32).astype(float), spark.createDataFrame([*rows, *odd], "vec_id long, embedding array<float>"), len(odd)


def test_near_vectors(spark):
    x, frame, odd = vectors(spark)
    rows = multiindex.near_vectors(frame).toPandas().sort_values("vec_id")
    assert len(rows) == len(x) + odd
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = u @ u.T >= 0.95
    np.fill_diagonal(near, False)
    links = rows.n_links.to_numpy()
    assert (links[: len(x)] <= near.sum(1)).all() and links.sum() >= 0.99 * near.sum() and (links[len(x) :] == 0).all()
    a, b = forest(*np.nonzero(near))
    low = dict(zip(a.tolist(), b.tolist(), strict=True))
    want = [low.get(i, i) for i in range(len(x))] + list(range(len(x), len(x) + odd))
    assert np.mean(rows.component_id.to_numpy() == want) > 0.99 and (rows.kept == (rows.vec_id == rows.component_id)).all()


def test_near_vectors_with_full_cells_are_split(spark):
    x, frame, _ = vectors(spark)
    plain = multiindex.near_vectors(frame).toPandas().sort_values("vec_id").reset_index(drop=True)
    split = multiindex.near_vectors(frame, multiindex.IndexConfig(chunk=7, visitors=11)).toPandas().sort_values("vec_id").reset_index(drop=True)
    assert plain.equals(split)


def test_near_vectors_repeats_and_empty(spark):
    frame = spark.createDataFrame([(1, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, [0.0, 1.0]), (None, [0.0, 1.0])], "vec_id long, embedding array<double>")
    got = sorted(((r.vec_id, r.n_links, r.component_id, r.kept) for r in multiindex.near_vectors(frame).collect()), key=str)
    assert got == sorted([(1, 2, 1, True)] * 2 + [(2, 2, 1, False), (3, 1, 3, True), (None, 1, 3, False)], key=str)
    assert multiindex.near_vectors(frame.limit(0)).count() == 0


def test_near_vectors_of_any_size_and_width(spark):
    rows = [(1, [1e200, 2e200]), (2, [2e200, 4.1e200]), (3, [1e-310, 2e-310]), (4, [1.0, 0.0]), (5, [1.0, 2.0, 3.0]), (6, [2.0, 4.0, 6.1]), (7, [-1.0, 2.0, 3.0]), (8, [5.0]), (9, [7.0]), (10, [])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("d", F.lit("clash"))
    got = {r.vec_id: (r.n_links, r.component_id) for r in multiindex.near_vectors(frame).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 3: (2, 1), 4: (0, 4), 5: (1, 5), 6: (1, 5), 7: (0, 7), 8: (1, 8), 9: (1, 8), 10: (0, 10)}


def test_traversal_is_by_summed_distance():
    rng = np.random.default_rng(0)
    x, books = rng.normal(size=(40, 8)), (rng.normal(size=(6, 4)), rng.normal(size=(7, 4)))
    cells = multiindex.traversal(x, books, 9)
    cost = (((x[:, None, :4] - books[0]) ** 2).sum(2)[:, :, None] + ((x[:, None, 4:] - books[1]) ** 2).sum(2)[:, None, :]).reshape(40, -1)
    assert (cells == np.argsort(cost, 1)[:, :9]).all()


def brute_topk(ids, x, every, k):
    v, out = np.floor(x * 64), []
    for i in np.flatnonzero(ids % every == 0):
        s = v @ v[i]
        order = [j for j in np.lexsort((ids, -s)) if j != i][:k]
        out += [(int(ids[i]), n + 1, int(ids[j]), int(s[j])) for n, j in enumerate(order)]
    return sorted(out)


@pytest.mark.parametrize("block", [7, 512])
def test_exact_topk(spark, block):
    x, frame, _ = vectors(spark)
    cfg = topk.TopkConfig(block=block, blocks_per_task=3, query_group=11, sample=64)
    got = sorted(tuple(r) for r in topk.exact_topk(frame, cfg).collect())
    ids = np.arange(len(x) + 2)  # the zero vector takes part, and its neighbour does not
    kept = np.append(np.arange(len(x)), len(x) + 1)
    assert got == brute_topk(ids[kept], np.vstack([x, np.zeros(16)]), 20, 20)


def test_topk_small_large_values_and_empty(spark):
    frame = spark.createDataFrame([(0, [3e15, 1.0]), (1, [2.0, 5.0]), (20, [-1.0, 1.5]), (None, [1.0, 1.0])], "vec_id long, embedding array<double>")
    got = sorted(tuple(r) for r in topk.exact_topk(frame, topk.TopkConfig(scale=1)).collect())
    assert got == [(0, 1, 1, 6 * 10**15 + 5), (0, 2, 20, -3 * 10**15 + 1), (20, 1, 1, 3), (20, 2, 0, -3 * 10**15 + 1)]
    assert topk.exact_topk(frame.limit(0)).count() == 0


def test_topk_repeated_ids_other_widths_and_huge_components(spark):
    rows = [(0, [1.0, 2.0]), (0, [2.0, 1.0]), (1, [3.0, 0.0]), (20, [1.0]), (21, [2.0]), (22, []), (40, [1e300, 1e308, 0.0]), (41, [1e300, 1e308, 1.0]), (42, [-1e200, 0.0, 0.0]), (43, [-1e201, 0.0, 0.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("row", F.lit("clash"))
    got = sorted(tuple(r) for r in topk.exact_topk(frame, topk.TopkConfig(scale=1)).collect())
    most = (1 << 63) - 1
    assert got == sorted([(0, 1, 0, 4), (0, 2, 1, 3), (0, 1, 1, 6), (0, 2, 0, 4), (20, 1, 21, 2), (40, 1, 41, most), (40, 2, 42, -most), (40, 3, 43, -most)])


def test_topk_ships_only_pairs_that_bounds_leave_open(spark):
    """On vectors in groups each query stays with its own, so pairs grow as the rows and not as their square."""
    shipped = {}
    for n in (400, 1600):
        rng = np.random.default_rng(1)
        group = np.arange(n) // 100
        signs = np.array([[1.0 if g >> i & 1 else -1.0 for i in range(8)] for g in range(16)])
        x = signs[group] * rng.uniform(0.9, 1.0, (n, 8))
        frame = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
        cfg = topk.TopkConfig(k=5, every=2, block=10, blocks_per_task=10, sample=4096)
        rows = topk.staged(topk.scaled(frame, 8, cfg).withColumn("row", F.monotonically_increasing_id()), "scaled")
        blocks = rows.repartitionByRange(n // 100, "code", "row").sortWithinPartitions("code", "row").select("row", "vec_id", "v").mapInArrow(topk._gathered(10), "rows binary, ids binary, x binary")
        blocks = topk.staged(blocks.withColumn("super", F.spark_partition_id().cast("long")), "blocks")
        asked = rows.where("vec_id % 2 = 0").withColumn("g", F.lit(0).cast("long"))
        shipped[n] = topk.live_pairs(topk._floors(rows, asked, n, 8, cfg), blocks, 1, 8, cfg).count()
        assert sorted(tuple(r) for r in topk.exact_topk(frame, cfg).collect()) == brute_topk(np.arange(n), x, 2, 5)
    assert shipped[1600] <= 8 * shipped[400] < 8 * 200 * 4


def test_shards(spark, docs_of, table_dir):
    rows = [(i, "t" * (i % 5)) for i in range(2000)] + [(3, "dup"), (3, "dup"), (None, None), (None, "x")]
    out = QUERIES["op5_shards"](spark, table_dir(documents=docs_of(rows).withColumn("shard", F.lit("clash")))).toPandas()
    assert len(out) == len(rows) and set(out.law) == {"key"}
    for s, part in out.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))
        assert 180 < len(part) < 330
    moved = out[out.shard != out.grown_shard]
    assert set(moved.grown_shard) == {8} and 0.05 < len(moved) / len(out) < 0.18
    assert out[out.doc_id == 3].shard.nunique() == 1
    null = out[out.doc_id.isna()]
    assert sorted(zip(null["size"], null.text_crc32, strict=True)) == sorted([(1, 0), (2, zlib.crc32(b"x"))])
    assert QUERIES["op5_shards"](spark, table_dir(documents=docs_of(rows).limit(0))).count() == 0


def test_shards_by_plain_python(spark, docs_of, table_dir):
    """The shard of every key, recomputed draw by draw."""
    rows = [(i * 7919 - 300, f"text {i}") for i in range(400)]
    out = QUERIES["op5_shards"](spark, table_dir(documents=docs_of(rows))).toPandas()

    def choose(key, n):
        draw = lambda s: -np.log(((spark_hash((key,), s, 7) >> 11) + 0.5) / 2.0**53)
        return min(range(n), key=draw)

    assert [choose(i, 8) for i in out.doc_id.tolist()] == out.shard.tolist()
    assert [choose(i, 9) for i in out.doc_id.tolist()] == out.grown_shard.tolist()


def test_weighted_shards(spark):
    got = spark.range(30_000).select(shards.choose(F.col("id"), [1.0, 0.0, 2.0]).alias("s")).groupBy("s").count().collect()
    counts = {r.s: r["count"] for r in got}
    assert set(counts) == {0, 2} and abs(counts[2] / counts[0] - 2) < 0.1
    with pytest.raises(ValueError, match="weight"):
        shards.choose(F.lit(1), [0.0])


def test_word_cache_equals_the_tokenizer():
    cache = packing.WordCache(packing.word_tokenizer())
    for text in ("Café x́ ́y <|endoftext|>a\x1cb\x85c d", "İSTANBUL ΣΑΣ. ﬁ. ²... x².", "", "...", "é. %. a%. don't. 's. IT'S!", "<|ENDOFTEXT|> A.", "١٢٣. ๑. Ⅷ:"):
        want = np.array(cache.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        assert cache.ids(text.encode()) == want


@pytest.mark.parametrize("seed", range(4))
def test_plan_places_every_length_once(seed):
    rng = np.random.default_rng(seed)
    limit = 64
    histogram = np.bincount(np.minimum(rng.geometric(0.06, 3000), limit), minlength=limit + 1)
    histogram[limit] += 50 * seed
    runs, bins = packing.plan(histogram, limit)
    seen = np.zeros(limit + 1, np.int64)
    room = {}
    for r in runs.itertuples(index=False):
        assert r.first == seen[r[0]]
        seen[r[0]] += r.n
        for i in range(r.n):
            room.setdefault(r.bin + i // r.each, []).append((r.at + i % r.each * r[0], r[0]))
    assert (seen == histogram).all() and sorted(room) == list(range(bins))
    for placed in room.values():
        at = 0
        for offset, length in sorted(placed):
            assert offset == at
            at += length
        assert at <= limit
    assert bins <= -(-int((np.arange(limit + 1) * histogram).sum()) // limit) * 1.01 + 2


def test_nnls_recovers_counts():
    rows, columns = np.array([1, 3, 2, 2, 4]), np.array([0, 0, 1, 1, 2])
    assert np.allclose(packing.nnls(rows, columns, np.array([0, 5.0, 8, 5, 3]), 3), [5, 4, 3], atol=1e-3)


def check_packing(out, ids_of, limit=packing.LIMIT):
    sums = out.sort_values(["sequence_id", "offset"])
    assert ((sums.groupby("sequence_id").length.cumsum() - sums.length) == sums.offset).all()
    assert sums.groupby("sequence_id").length.sum().max() <= limit
    for doc, part in out.sort_values("piece").groupby("doc_id"):
        if doc not in ids_of:
            continue
        ids = ids_of[doc]
        for r in part.itertuples():
            piece = ids[r.start : r.start + r.length]
            assert r.start == r.piece * limit and zlib.crc32(np.array(piece, "<u4").tobytes()) == r.ids_crc32
        assert part.length.sum() == len(ids)


def test_packing_query(spark, docs_of, table_dir):
    cache = packing.WordCache(packing.word_tokenizer())
    texts = {i: f"word{i % 7} " * (i * 37 % 900) for i in range(120)} | {500: "long text " * 9000, 501: ""}
    docs = docs_of([*texts.items(), (502, None), (None, "no id"), (7, texts[7])]).withColumn("length", F.lit("clash"))
    out = QUERIES["op7_packing"](spark, table_dir(documents=docs)).toPandas()
    ids = {i: [*cache.tokenizer.encode(t, add_special_tokens=False).ids, 1] for i, t in texts.items() if i != 7}
    check_packing(out, ids | {502: [1]})
    assert out.sequence_id.nunique() <= -(-int(out.length.sum()) // packing.LIMIT) + 1
    assert QUERIES["op7_packing"](spark, table_dir(documents=docs.limit(0))).count() == 0
    with_ids = packing.pieces(docs, packing.word_tokenizer(), with_ids=True).where("doc_id = 500").orderBy("piece").collect()
    assert np.frombuffer(b"".join(r.ids for r in with_ids), "<u4").tolist() == ids[500]


def plain_targets(sizes):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    total, capped = sum(sizes.values()), set()
    while True:
        rest = [s for s in names if s not in capped]
        left, w = total - sum(3 * sizes[s] for s in capped), sum(weight[s] for s in rest)
        over = {s for s in rest if left * weight[s] / w > 3 * sizes[s] + 1e-9}
        if not over:
            return {s: 3 * sizes[s] if s in capped else left * weight[s] / w for s in names}
        capped |= over


def test_mixture(spark, docs_of, table_dir):
    rng = np.random.default_rng(5)
    rows = []
    for i in range(900):
        source = [None, "b", "a", "é", "hot", "tiny", ""][rng.choice(7, p=[0.1, 0.15, 0.15, 0.1, 0.44, 0.01, 0.05])]
        rows.append((i, " ".join(f"w{i}x{k}" for k in range(rng.integers(0, 300))), source))
    rows += [(5, "again and again", "a"), (5, "again and again", "a"), (None, "no id", "b"), (901, None, "b"), (902, "  \x1c\n", "b")]
    path = table_dir(documents=docs_of(rows).withColumn("size", F.lit("clash")))
    out = QUERIES["op9_mixture"](spark, path)
    again = QUERIES["op9_mixture"](spark, path)
    assert sorted(map(str, out.collect())) == sorted(map(str, again.collect()))
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    sizes = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + size(t)
    want = plain_targets(sizes)
    got = out.toPandas()
    assert len(got) == len(rows) and (got.taken <= 3 * got["size"]).all()
    assert sorted(got["size"]) == sorted(size(t) for _, t, _ in rows)
    source_of = {i: s for i, _, s in rows if i is not None and i != 5}
    for s, t in want.items():
        part = got[[source_of.get(i, "none") == s for i in got.doc_id]]
        assert (np.abs(part.target - t) < 1e-6).all() and (part.source_size == sizes[s]).all()
        assert abs(part.taken.sum() - t) <= 4 * (16 * t) ** 0.5 + 32  # slots of 16 words: four deviations
    assert QUERIES["op9_mixture"](spark, table_dir(documents=docs_of(rows).limit(0))).count() == 0
    assert not re.search("Python|Arrow|Pandas", out._jdf.queryExecution().executedPlan().toString())


def spark_hash(*values):
    """64-bit hash of a row of values as the engine defines it: strings as bytes, long numbers as 8 and others as 4 of them, nulls left out."""
    h = 42
    for v in values:
        if v is not None:
            data = v.encode() if isinstance(v, str) else struct.pack("<q", v[0]) if isinstance(v, tuple) else struct.pack("<i", int(v))
            h = xxhash.xxh64_intdigest(data, h)
    return h


def signed(h):
    return h - (1 << 64) if h >> 63 else h


def plain_mix(rows, cfg):
    """taken by doc_id, slot by slot, from (doc_id, words, source) rows with ids of their own."""
    sizes, order = {}, {}
    for i, n, s in rows:
        sizes[s] = sizes.get(s, 0) + n
    for i, n, s in sorted(rows, key=lambda r: (signed(spark_hash((r[0],), cfg.seed)) % cfg.buckets, r[0])):
        order.setdefault(s, []).append((i, n))
    names = sorted((s for s in sizes if sizes[s]), key=lambda s: (s is None, s or ""))
    goal = plain_targets(sizes)
    blocks = {s: -(-sizes[s] // cfg.block_words) for s in names}
    want = np.array([goal[s] * blocks[s] / sizes[s] for s in names])
    edges = np.cumsum(want) / want.sum()
    edges[-1] = 1.0
    counts = {}
    for slot in range(round(want.sum())):
        u = (spark_hash(cfg.seed, "draw", (slot,)) >> 11) / 2.0**53
        s = names[int(np.searchsorted(edges, u, side="right"))]
        counts[s] = counts.get(s, 0) + 1
    taken = {}
    for s in names:
        times, n = {}, blocks[s]
        for slot in range(min(counts.get(s, 0), 3 * n)):
            x, keys = slot % n, (s or "", s is None, (slot // n,), cfg.seed)
            for r in range(cfg.rounds):
                other = (signed(spark_hash(r, *keys)) % n - x) % n
                if spark_hash((max(x, other),), r, 1, *keys) % 2 == 0:
                    x = other
            times[x] = times.get(x, 0) + 1
        at = 0
        for i, size in order[s]:
            taken[i] = sum(times.get((at + k) // cfg.block_words, 0) for k in range(size))
            at += size
    return counts, taken


def test_mixture_slot_by_slot(spark, docs_of):
    """Draws, permutations and words taken, recomputed without Spark."""
    rng = np.random.default_rng(8)
    rows = [(i, int(rng.integers(0, 60)), ["a", "b", None, "hot", ""][min(4, int(rng.exponential(1.2)))]) for i in range(160)]
    cfg = mixture.MixConfig(block_words=4, shard_slots=100, cells=8)
    kept, sources, taken = mixture.mixed(docs_of([(i, "w " * n, s) for i, n, s in rows]), cfg)
    sums = taken.groupBy("_src", "_start").agg(F.sum(F.col("_len") * F.col("_times")).alias("t"))
    same = kept["_src"].eqNullSafe(sums["_src"]) & (kept["_start"] == sums["_start"])
    got = {r.doc_id: r.t for r in kept.where("_size > 0").join(sums, same).select("doc_id", "t").collect()}
    counts, want = plain_mix(rows, cfg)
    drawn = {r._src: r.n for r in mixture.shard_counts(sources, cfg).groupBy("_src").agg(F.sum("_count").alias("n")).collect()}
    assert drawn == counts
    assert got == {i: want[i] for i, n, _ in rows if n}


def test_shard_counts_are_multinomial(spark):
    """Counts of shards scatter as independent draws do, about their expectation."""
    cfg = mixture.MixConfig(block_words=1, shard_slots=500)
    sources = spark.createDataFrame([("a", 60_000, 60_000.0), ("b", 30_000, 30_000.0), (None, 10_000, 10_000.0)], "_src string, source_size long, target double")
    rows = mixture.shard_counts(sources, cfg).toPandas()
    assert rows.groupby("_shard")._count.sum().eq(500).all() and rows._shard.nunique() == 200
    for source, p in (("a", 0.6), ("b", 0.3)):
        counts = rows[rows._src == source]._count
        assert abs(counts.mean() - 500 * p) < 4 * (500 * p * (1 - p) / 200) ** 0.5
        assert 0.7 < counts.var() / (500 * p * (1 - p)) < 1.35


def test_stages_leave_columns_of_any_name_alone(spark, docs_of):
    texts = ["alpha beta gamma delta epsilon", "alpha beta gamma delta epsilon", "one two three\nfour five six", None]
    names = ["_key", "_base", "_gone", "_rest", "_size", "_src", "_start", "_kept", "_h1", "h1", "first", "fp", "row", "_words", "_times", "_doc"]
    docs = docs_of([(i, t, "s") for i, t in enumerate(texts)])
    for name in names:
        docs = docs.withColumn(name, F.concat(F.lit(f"{name} of "), F.col("doc_id").cast("string")))
    for stage in (lines.dedup, simhash.keep_one, mixture.mix_documents):
        out = stage(docs)
        assert out.columns == docs.columns and [f.dataType for f in out.schema] == [f.dataType for f in docs.schema]
        got = out.collect()
        assert got and all(r[name] == f"{name} of {r.doc_id}" for r in got for name in names)


def test_permutation_is_one(spark):
    for n in (1, 2, 7, 1000):
        frame = spark.range(n).select(mixture.permuted(F.col("id"), F.lit(n).cast("long"), F.lit("s"), rounds=16).alias("p"))
        assert sorted(r.p for r in frame.collect()) == list(range(n))


def test_mixed_documents_have_the_words_taken(spark, docs_of):
    rows = [(i, " ".join(f"w{i}x{k}" for k in range(5 + i % 200)), "abc"[i % 3]) for i in range(240)]
    docs = docs_of(rows)
    out = mixture.mix_documents(docs)
    assert out.columns == docs.columns
    rows_, _, taken = mixture.mixed(docs)
    sums = taken.groupBy("_src", "_start").agg(F.sum(F.col("_len") * F.col("_times")).alias("t"))
    want = {r.doc_id: r.t for r in rows_.join(sums, ["_src", "_start"]).collect() if r.t}
    texts = dict((i, t) for i, t, _ in rows)
    got = {r.doc_id: r.text for r in out.collect()}
    assert {i: len(t.split()) for i, t in got.items()} == want
    assert all(set(t.split()) <= set(texts[i].split()) for i, t in got.items())


def test_pipeline(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    before = docs.count()
    frame = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        frame = corpus_pipeline.staged(stage(spark, frame, sf), name)
        assert frame.columns == docs.columns
        if name == "quality":
            marks = spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").join(docs, "doc_id").count()
            assert frame.join(spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1"), "doc_id").count() >= 0.97 * marks
        if name == "simhash":
            assert frame.select("doc_id").distinct().count() == frame.count() < before
    out = corpus_pipeline.run(spark, sf).toPandas()
    cache = packing.WordCache(packing.word_tokenizer())
    ids = {r.doc_id: [*np.frombuffer(cache.ids(r.text.encode()), "<u4").tolist(), 1] for r in frame.collect()}
    assert set(out.doc_id) == set(ids)
    check_packing(out, ids)
    for r in out.itertuples():
        assert np.frombuffer(r.ids, "<u4").tolist() == ids[r.doc_id][r.start : r.start + r.length]


def test_pipeline_stages_by_plain_python(spark, docs_of, table_dir):
    """Each stage's whole result on a small table against what plain Python makes of the same input."""
    from test_text_operators import brute_lines, plain_fingerprint

    rng = np.random.default_rng(4)
    vocabulary = [f"word{i}" for i in range(400)]
    lines_ = [" ".join(rng.choice(vocabulary, 12)) for _ in range(60)]
    texts = ["\n".join(lines_[k] for k in rng.integers(0, 60, 4)) for _ in range(50)]
    texts += [" ".join(rng.choice(vocabulary, 90)) for _ in range(10)] + ["spam spam spam " * 20] * 5 + ["", None]
    texts += [texts[52] + " tail", texts[53]]
    docs = docs_of([(i, t, "ab"[i % 2]) for i, t in enumerate(texts)])
    labels = spark.createDataFrame([(i, int("spam" not in (t or "")), 0) for i, t in enumerate(texts)], "doc_id long, quality int, toxic int")
    path = table_dir(documents=docs, labels=labels)
    stages = dict(corpus_pipeline.STAGES)
    kept = stages["quality"](spark, docs, path)
    assert {r.doc_id for r in kept.collect()} >= {i for i, t in enumerate(texts) if t and "spam" not in t}
    after = {r.doc_id: r.text for r in stages["line_dedup"](spark, docs, path).collect()}
    gone = brute_lines(list(enumerate(texts)))
    assert after == {i: None if t is None else "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone) for i, t in enumerate(texts)}
    left = {r.doc_id for r in stages["simhash"](spark, docs, path).collect()}
    fp = [plain_fingerprint(t) for t in texts]
    a, b = np.nonzero(np.bitwise_count(np.array(fp, np.uint64)[:, None] ^ np.array(fp, np.uint64)[None, :]) <= 4)
    high, _ = forest(a, b)
    assert left == set(range(len(texts))) - set(high.tolist())


def test_pipeline_on_odd_rows(spark, docs_of, table_dir):
    texts = ["", None, "a", "one two three four five six", "one two three four five six", "x " * 9000, "line\nline\nother words here"]
    docs = docs_of([*enumerate(texts), (1, "one more"), (None, "null id text of some words")]).withColumn("_key", F.lit(1))
    labels = spark.createDataFrame([(2, 1, 0)], "doc_id long, quality int, toxic int")
    path = table_dir(documents=docs, labels=labels, )
    assert corpus_pipeline.run(spark, path).count() > 0
    empty = table_dir(documents=docs.limit(0), labels=labels.limit(0))
    assert corpus_pipeline.run(spark, empty).count() == 0


def test_packing_hands_texts_over_in_small_batches_and_leaves_the_setting(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)

    def sizes(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows], pa.int64())], ["n"])

    seen = spark.range(2000, numPartitions=1).mapInArrow(sizes, "n long")
    with packing.small_batches(spark):
        assert spark.conf.get(name) == str(packing._IN)
        found = [r["n"] for r in seen.collect()]
    assert sum(found) == 2000 and max(found) == packing._IN
    assert spark.conf.get(name) == before
