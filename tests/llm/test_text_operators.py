"""Quality, line dedup, SimHash, licences: against plain Python."""

import itertools
import math
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from comparing import same
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from detspark.llm import licences, lines, quality, simhash
from detspark.llm import text as tx
from detspark.llm.catalogue import ORACLES, QUERIES
from detspark.llm.graph import components, forest

ODD = ["", None, " \t\n", "a", "one two", "x" * 5000, "wörd " * 700, "a b c d e f g h i j\n" * 400, "\n\n\n", "tie tie tie"]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="ab C.!é\n\t ", max_size=40), max_size=6), st.integers(1, 30))
def test_spans_and_hashes_do_not_depend_on_chunks(texts, size):
    column = pa.array(texts, pa.string())
    offsets, data = tx.column_bytes(column)
    want = {}
    for row, text in enumerate(texts):
        want[row] = text.encode().split()
    got = {row: [] for row in range(len(texts))}
    for rows, bounds, chunk in tx.pieces(offsets, data, 1 - tx.BLANKS, size):
        starts, ends = tx.spans(chunk, tx.BLANKS, bounds)
        hashes = tx.hash_spans(chunk, starts, ends)
        for s, e, h in zip(starts, ends, hashes, strict=True):
            row = rows[np.searchsorted(bounds, s, side="right") - 1]
            got[int(row)].append((chunk[s:e].tobytes(), int(h)))
    assert {r: [w for w, _ in v] for r, v in got.items()} == want
    by_word = {}
    for w, h in itertools.chain(*got.values()):
        assert by_word.setdefault(w, h) == h
    assert len(set(by_word.values())) == len(by_word)


def test_quality_learns_and_holds_out(spark, sf):
    rows = QUERIES["op1_quality"](spark, sf).toPandas()
    marks = spark.read.parquet(f"{sf}/labels.parquet").toPandas()
    both = rows.merge(marks, on="doc_id")
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()
    assert rows.score.between(0, 1).all() and (rows.predicted == (rows.score >= 0.3)).all()
    assert (rows.held_out == [zlib.crc32(str(i).encode()) % 5 == 0 for i in rows.doc_id]).all()
    good = both.quality == 1
    assert (both.predicted == both.quality).mean() > 0.9 and both[good].predicted.mean() > 0.97


def test_quality_held_out_accuracy_on_more_rows(spark):
    sf = "/root/testdata/sf0.1"
    rows = QUERIES["op1_quality"](spark, sf).toPandas().merge(spark.read.parquet(f"{sf}/labels.parquet").toPandas(), on="doc_id")
    held = rows[rows.held_out]
    assert (held.predicted == held.quality).mean() > 0.97


def plain_buckets(text, bits):
    """Hashed words and word pairs of a text, one by one."""
    data = text.encode()
    kinds, spans, start = tx.CLASSES[np.frombuffer(data, np.uint8)].tolist() if data else [], [], None
    for at in range(len(data) + 1):
        if start is not None and (at == len(data) or kinds[at] != kinds[start]):
            spans.append((start, at))
            start = None
        if start is None and at < len(data) and kinds[at]:
            start = at
    hashes = []
    for low, high in spans:
        one = np.frombuffer(data[low:high], np.uint8)
        hashes.append(int(tx.hash_spans(one, np.array([0]), np.array([len(one)]))[0]))
    mask = (1 << bits) - 1
    out = [h & mask for h in hashes]
    for a, b in itertools.pairwise(hashes):
        out.append(int(quality._TWICE) & mask if a == b else int(tx.mix(np.array([(3 * a + b) % (1 << 64)], np.uint64))[0]) & mask)
    return out


def plain_ftrl(rows, cfg):
    """Weights by bucket (-1: bias), coordinate by coordinate in plain Python."""
    z, n = {}, {}

    def weight(i):
        if abs(z.get(i, 0.0)) <= cfg.l1:
            return 0.0
        return -(z[i] - math.copysign(cfg.l1, z[i])) / ((cfg.beta + math.sqrt(n.get(i, 0.0))) / cfg.alpha + cfg.l2)

    for _ in range(cfg.epochs):
        for text, y in rows:
            buckets = plain_buckets(text, cfg.bits)
            x = {b: buckets.count(b) / math.sqrt(len(buckets)) for b in buckets} | {-1: 1.0}
            w = {i: weight(i) for i in x}
            p = 1 / (1 + math.exp(-sum(w[i] * v for i, v in x.items())))
            for i, v in x.items():
                g = (p - y) * v
                z[i] = z.get(i, 0.0) + g - (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / cfg.alpha * w[i]
                n[i] = n.get(i, 0.0) + g * g
    return {i: weight(i) for i in z}


def test_quality_weights_and_scores_by_plain_python(spark, docs_of):
    rng = np.random.default_rng(2)
    texts = [" ".join(rng.choice(["good", "fine", "text", "of", "words", "words.", "Ünï"], rng.integers(1, 30))) for _ in range(40)] + ["", "spam spam spam", "spam spam !!"]
    labels = [int("spam" not in t and i % 5 > 0) for i, t in enumerate(texts)]
    cfg = quality.QualityConfig(bits=10, epochs=2)
    docs = docs_of(list(enumerate(texts)))
    weights = quality.train(docs, spark.createDataFrame(list(enumerate(labels)), "doc_id long, quality int"), cfg)
    order = sorted(range(len(texts)), key=lambda i: (i * 0x9E3779B97F4A7C15 + 11) % (1 << 64))
    want = plain_ftrl([(texts[i], labels[i]) for i in order], cfg)
    dense = np.array([want.get(i, 0.0) for i in [*range(1 << 10), -1]])
    assert np.allclose(weights, dense, atol=1e-5) and (weights != 0).sum() > 20
    for r in quality.score(docs, weights, cfg=cfg).collect():
        b = plain_buckets(r.text, cfg.bits)
        assert abs(r.score - 1 / (1 + math.exp(-sum(dense[k] for k in b) / math.sqrt(max(1, len(b))) - dense[-1]))) < 1e-5


def test_quality_edges(spark, docs_of, table_dir):
    docs = docs_of([*enumerate(ODD), (3, "a"), (3, "a"), (None, "null id")])
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(len(ODD))], "doc_id long, quality int, toxic int")
    out = QUERIES["op1_quality"](spark, table_dir(documents=docs.withColumn("score", F.lit("x")).withColumn("_y", F.lit(1)), labels=labels)).collect()
    assert len(out) == docs.count() and all(0 <= r.score <= 1 for r in out)
    empty = QUERIES["op1_quality"](spark, table_dir(documents=docs, labels=labels.limit(0))).collect()
    assert {r.score for r in empty} == {0.5}
    assert QUERIES["op1_quality"](spark, table_dir(documents=docs.limit(0), labels=labels)).count() == 0


def test_quality_scores_whole_texts():
    cfg = quality.QualityConfig(bits=12)
    w = np.random.default_rng(0).normal(size=(1 << 12) + 1).astype(np.float32)
    long = " ".join(f"w{i % 977}" for i in range(400_000))
    keep = tx.CHUNK
    try:
        whole = quality._scores(pa.array([long, "b"]), w, cfg.bits)
        tx.CHUNK = 1 << 30
        assert abs(quality._scores(pa.array([long, "b"]), w, cfg.bits) - whole).max() < 1e-9
    finally:
        tx.CHUNK = keep


def brute_lines(rows, t=0.8):
    """(doc, line) that an earlier line matches."""
    fold = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
    places = []
    for i, text in sorted(((i, x) for i, x in rows if x is not None), key=lambda r: r[0]):
        for k, line in enumerate(text.split("\n")):
            words = frozenset(w for w in re.split("[ \t\n\r\x0b\x0c]+", line.translate(fold)) if w)
            if words:
                places.append((i, k, words))
    out = set()
    for n, (i, k, w) in enumerate(places):
        for _, _, v in places[:n]:
            if len(w & v) >= t * len(w | v) - 1e-9:
                out.add((i, k))
                break
    return out


def test_line_dedup_against_brute_force(spark, docs_of):
    rng = np.random.default_rng(3)
    vocabulary = [f"w{i}" for i in range(60)]
    base = [list(rng.choice(vocabulary, rng.integers(1, 150))) for _ in range(40)]
    rows = []
    for i in range(160):
        picked = []
        for _ in range(rng.integers(1, 4)):
            line = list(base[rng.integers(len(base))])
            for _ in range(rng.integers(0, 3)):
                line[rng.integers(len(line))] = str(rng.choice(vocabulary))
            picked.append(" ".join(line))
        rows.append((i, "\n".join(picked)))
    docs = lines.keyed(docs_of(rows))
    got = {(r.doc, r.line) for r in lines.removed_lines(docs.select("_key", "text")).collect()}
    assert got == brute_lines(rows)


def test_line_dedup_of_a_large_group_of_near_copies(spark, docs_of):
    words = [f"k{i}" for i in range(30)]
    rows = [(i, " ".join([*words, f"own{i}"])) for i in range(1500)]
    docs = lines.keyed(docs_of(rows))
    got = {r.doc for r in lines.removed_lines(docs.select("_key", "text")).collect()}
    assert got == set(range(1, 1500))


def test_line_dedup_edges(spark, docs_of):
    rows = [*enumerate(ODD), (20, "one two\nthree"), (21, "ONE  two"), (21, "ONE  two"), (None, "one two")]
    out = lines.dedup(docs_of(rows).withColumn("line", F.lit(7)).withColumn("doc", F.lit("d")))
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "line", "doc"]
    got = {(r.doc_id, r.text) for r in out.collect()}
    assert out.count() == len(rows)
    assert (4, "one two") in got and (20, "three") in got and (21, "") in got and (None, "") in got and (1, None) in got and (8, "\n\n\n") in got
    assert lines.dedup(docs_of(rows).limit(0)).count() == 0
    twice = lines.dedup(out.drop("line", "doc"))
    assert sorted(map(str, twice.select("doc_id", "text").collect())) == sorted(map(str, out.select("doc_id", "text").collect()))


def test_wanted_lines_of_texts_that_end_in_line_ends():
    texts = ["abc\n", "x def", "", "\n", "a\n\n", None, "b\nc\n", "", "last"]
    every = np.full(1 << 10, 255, np.uint8)
    for some in (texts, [x for x in texts if x]):
        got = [(r, k, x) for rows, numbers, text in lines._wanted_lines(pa.array(some, pa.string()), np.arange(len(some)), every) for r, k, x in zip(rows.tolist(), numbers.tolist(), text.decode().split("\n"), strict=True)]
        assert got == [(i, k, x) for i, text in enumerate(some) for k, x in enumerate((text or "").split("\n"))]


@pytest.mark.parametrize("between", [(), ("",), ("\n", "")])
def test_line_dedup_of_texts_that_end_in_line_ends(spark, docs_of, between):
    rng = np.random.default_rng(5)
    texts = []
    for i in range(60):
        words = [f"g{i % 12}w{k}" for k in range(20)]
        words[rng.integers(20)] = f"own{i}"
        texts += [" ".join(words) + "\n" * int(rng.integers(1, 4)) + f"rest of {i}\n", *between]
    rows = list(enumerate(texts))
    got = {(r.doc, r.line) for r in lines.removed_lines(lines.keyed(docs_of(rows)).select("_key", "text")).collect()}
    assert got == brute_lines(rows) and got


def test_line_dedup_keeps_one_copy_of_repeated_rows(spark, docs_of, table_dir):
    near = " ".join(f"n{i}" for i in range(20))
    rows = [(1, "first"), (7, "alone here\nand more"), (7, "alone here\nand more"), (8, "shared\nfirst"), (8, "first\nown line"), (9, "shared")]
    rows += [(None, "no id\nat all")] * 3 + [(None, None)] * 2 + [(10, f"{near} x"), (10, f"{near} y")]
    for frame in (docs_of(rows), docs_of(rows).repartition(3), docs_of(rows).coalesce(1)):
        got = sorted(((r.doc_id, r.text) for r in lines.dedup(frame).collect()), key=str)
        ten = {x for i, x in got if i == 10}
        assert len(ten) == 2 and "" in ten and ten - {""} <= {f"{near} x", f"{near} y"}
        want = [(1, "first"), (7, "alone here\nand more"), (7, ""), (8, "shared"), (8, "own line"), (9, ""), (None, "no id\nat all"), (None, ""), (None, ""), (None, None), (None, None)]
        assert [x for x in got if x[0] != 10] == sorted(want, key=str)
    out = QUERIES["op3_line_dedup"](spark, table_dir(documents=docs_of(rows))).collect()
    assert sorted((r.n_lines, r.n_removed, r.kept_bytes) for r in out if r.doc_id == 7) == [(2, 0, 19), (2, 2, 0)]
    assert sorted((r.n_lines, r.n_removed) for r in out if r.doc_id is None) == [(0, 0), (0, 0), (2, 0), (2, 2), (2, 2)]


def test_line_numbers_over_chunks():
    text = "\n".join(f"line {i} " + "x " * 50 for i in range(30_000))
    seen = {}
    for row, line, word in lines._tokens(pa.array(["a\nb", text, "", "c"])):
        for r, k in zip(row.tolist(), line.tolist(), strict=True):
            seen.setdefault(r, set()).add(k)
    assert seen[1] == set(range(30_000)) and seen[0] == {0, 1} and seen[3] == {0}


def plain_fingerprint(text, k=4):
    words = [w for w in re.split("[ \t\n\x0b\x0c\r]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@settings(max_examples=50, deadline=None)
@given(st.text(alphabet="aB cÉ\n ", max_size=60))
def test_fingerprint(text):
    assert simhash.fingerprint(text.encode()) == plain_fingerprint(text)


def test_every_near_pair_meets_at_an_anchor():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 1 << 64, 400, dtype=np.uint64)
    y = x.copy()
    for _ in range(4):
        y ^= np.uint64(1) << rng.integers(0, 64, 400).astype(np.uint64)
    rx, kx, hx = simhash.anchors(x.view(np.int64))
    ry, ky, hy = simhash.anchors(y.view(np.int64))
    homes = {(int(r), int(k)) for r, k, h in zip(rx, kx, hx, strict=True) if h}
    visits = {(int(r), int(k)) for r, k, h in zip(ry, ky, hy, strict=True) if not h}
    assert {r for r, _ in homes & visits} == set(range(400))


def test_simhash_groups_against_brute_force(spark, sf):
    rows = QUERIES["op10_simhash"](spark, sf).toPandas()
    fp = np.array([int(x, 16) for x in rows.fingerprint], np.uint64)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert [plain_fingerprint(texts[i]) for i in rows.doc_id] == fp.tolist()
    a, b = np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 4)
    ids = rows.doc_id.to_numpy()
    u, v = forest(ids[a], ids[b])
    low = dict(zip(u.tolist(), v.tolist(), strict=True))
    assert [low.get(i, i) for i in ids.tolist()] == rows.component_id.tolist()


def test_simhash_edges(spark, docs_of):
    rows = [*enumerate(ODD), (30, "A"), (31, "one  TWO"), (31, "one  TWO"), (None, "null id here")]
    found = {(r.doc_id, r.fp): r.component_id for r in simhash.groups(docs_of(rows)).collect()}
    by_id = {i: c for (i, _), c in found.items()}
    assert by_id[0] == by_id[1] == by_id[2] == by_id[8] == 0 and by_id[30] == 3 and by_id[31] == 4
    kept = simhash.keep_one(docs_of(rows).withColumn("fp", F.lit("mine")))
    ids = [r.doc_id for r in kept.collect()]
    assert len(ids) == len(set(ids)) and set(ids) >= {0, 3, 4, None} and "fp" in kept.columns
    assert simhash.groups(docs_of(rows).limit(0)).count() == 0


def test_simhash_keeps_a_row_of_every_group(spark, docs_of):
    unlike = [" ".join(f"{chr(97 + i)}{k}" for k in range(12)) for i in range(8)]
    rows = [(None, unlike[0]), (None, unlike[1]), (None, unlike[1]), (5, unlike[2]), (5, unlike[3]), (6, unlike[4]), (None, unlike[4]), (7, unlike[4]), (5, unlike[6]), (4, unlike[6]), (None, unlike[5])]
    assert len({r.component_id for r in simhash.groups(docs_of(list(enumerate(unlike)))).collect()}) == len(unlike)
    kept = sorted(((r.doc_id, r.text) for r in simhash.keep_one(docs_of(rows)).collect()), key=str)
    assert kept == sorted([(None, unlike[0]), (None, unlike[1]), (5, unlike[2]), (5, unlike[3]), (6, unlike[4]), (4, unlike[6]), (None, unlike[5])], key=str)


def test_components(spark):
    rng = np.random.default_rng(2)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1200)] + [(5, 5)]
    got = {r.node: r.component for r in components(spark.createDataFrame(pairs, "u long, v long").repartition(7)).collect()}
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    want = {x: root(x) for x in parent if any(x in p and p[0] != p[1] for p in pairs)}
    assert got == want
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_licences_equal_their_twin(spark, sf, duck):
    assert same(QUERIES["op8_licences"](spark, sf).toPandas(), duck.execute(ORACLES["op8_licences"]).fetchdf())


def test_licence_edges(spark, docs_of):
    notice = "Released under the MIT License."
    rows = [*enumerate(ODD), (40, notice), (40, notice), (41, f"intro\n{notice.upper()}\nrest"), (42, "MIT"), (43, "released under the MIT licence agreement of old")]
    got = [(r.doc_id, r.line_no, r.licence) for r in licences.scan(docs_of(rows).withColumn("licence", F.lit(1)).withColumn("_pairs", F.lit(1))).collect()]
    assert sorted(got) == [(40, 1, "MIT"), (40, 1, "MIT"), (41, 2, "MIT")]
    assert licences.scan(docs_of(rows).limit(0)).count() == 0 and licences.scan(docs_of(rows), rows=()).count() == 0
    plan = licences.scan(docs_of(rows))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_licences_in_prose_over_lines_and_whole(spark, docs_of, tmp_path):
    """Whole texts, wrapped and embedded notices, and places of several in one document; the twin agrees."""
    import duckdb

    full = dict(licences.TEMPLATES)
    wrapped = re.sub(r"((?:\S+\s+){9}\S+)\s+", r"\1\n# ", full["MIT:text"])
    changed = full["BSD-3-Clause:text"].replace("COPYRIGHT HOLDERS AND CONTRIBUTORS", "REGENTS AND CONTRIBUTORS").replace("the copyright holder nor", "Some University nor")
    notice = full["BSD-3-Clause"]
    rows = [
        (1, "# Copyright (c) somebody\n# \n# " + wrapped + "\nimport this\n" * 30), (2, changed), (3, "def f():\n    pass\n" * 50 + notice[:48] + "\n" + notice[48:] + "\nmore"),
        (4, f"As they say, {full['MIT'].lower()} And then other things are told. " * 3), (5, f"{full['GPL-3.0']}\nsome text between them\n{full['GPL-3.0']}"), (6, "of the software in the work and the license " * 60), (7, None),
    ]
    docs = docs_of(rows)
    got = licences.scan(docs).collect()
    places = sorted((r.doc_id, r.line_no, r.licence) for r in got)
    assert {(1, 3, "MIT:text"), (2, 1, "BSD-3-Clause:text"), (3, 101, "BSD-3-Clause"), (5, 1, "GPL-3.0"), (5, 3, "GPL-3.0")} <= set(places)
    assert places.count((4, 1, "MIT")) == 3 and not [p for p in places if p[0] in (6, 7)]
    docs.coalesce(1).write.parquet(str(tmp_path / "d"))
    connection = duckdb.connect()
    connection.execute(f"create view documents as select * from '{tmp_path}/d/*.parquet'")
    twin = connection.execute(ORACLES["op8_licences"]).fetchall()
    assert sorted((r.doc_id, r.line_no, r.licence, round(r.dice, 9)) for r in got) == sorted(twin)


def test_sums_to_round_numbers():
    assert lines.prefix_length(np.array([1, 2, 5, 10])).tolist() == [n - math.ceil(0.8 * n - 1e-9) + 1 for n in (1, 2, 5, 10)]
