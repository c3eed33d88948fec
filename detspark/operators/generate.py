"""Coupled generation: from each source the configurations that the Hamiltonian connects it to.

All forms return the edges ``(s*, w*, h, kind)``: source words, target words, value, number of moved particles.  None of
them shuffles; parallelism follows the partitions of the space.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.functions import bits
from detspark.functions.schema import ProblemSpec, edge_schema, require
from detspark.operators.excite import Tables, padded


@dataclass(frozen=True)
class ScreenPolicy:
    """Which moves are dropped.  ``fixed``: \\|h\\| <= eps.  ``scaled``: \\|h psi_source\\| <= eps.  ``budget``: eps is a quantile of
    \\|h\\| on a sample of the sources, so that about ``edges`` moves are expected to stay.  The diagonal always stays."""

    kind: str = "fixed"
    eps: float = 0.0
    edges: int | None = None

    @staticmethod
    def fixed(eps: float) -> ScreenPolicy:
        return ScreenPolicy("fixed", eps)

    @staticmethod
    def scaled(eps: float) -> ScreenPolicy:
        return ScreenPolicy("scaled", eps)

    @staticmethod
    def budget(edges: int) -> ScreenPolicy:
        return ScreenPolicy("budget", 0.0, edges)


def screen(edges: DataFrame, spec: ProblemSpec, policy: ScreenPolicy, amps: DataFrame | None = None, share: float = 0.01) -> DataFrame:
    """Edges that the policy keeps.  ``scaled`` joins the amplitudes ``(w*, psi)`` of the sources."""
    off = F.col("kind") > 0
    if policy.kind == "fixed":
        return edges.where(~off | (F.abs("h") > policy.eps))
    if policy.kind == "scaled":
        known = amps.select(*[F.col(w).alias(s) for w, s in zip(spec.names, spec.source_names, strict=True)], F.abs("psi").alias("_psi"))
        joined = edges.join(known, spec.source_names, "left")
        return joined.where(~off | F.col("_psi").isNull() | (F.abs("h") * F.col("_psi") > policy.eps)).drop("_psi")
    sampled = edges.where(off & (F.pmod(F.xxhash64(*spec.source_names), F.lit(1_000_000)) < int(share * 1_000_000)))
    n, low = sampled.agg(F.count("*"), F.min(F.abs("h"))).first()
    expected = n / share
    if not n or expected <= policy.edges:
        return edges
    cut = sampled.agg(F.percentile_approx(F.abs(F.col("h").cast("double")), 1.0 - policy.edges / expected, 10_000)).first()[0]
    return screen(edges, spec, ScreenPolicy.fixed(cut))


def dropped_weight(before: DataFrame, after: DataFrame) -> DataFrame:
    """Sum of \\|h\\| that screening took away."""
    total = lambda f: f.agg(F.coalesce(F.sum(F.abs("h")), F.lit(0)).alias("w"))
    return total(before).withColumnRenamed("w", "a").join(total(after)).select((F.col("a") - F.col("w")).alias("dropped"))


#: largest excitation table, in bytes, that is sent to every task; larger ones are joined by a shuffle
BROADCAST = 64 << 20


def _sent(frame: DataFrame, rows: int, width: int) -> DataFrame:
    """``frame`` marked for broadcast if ``rows`` rows of about ``width`` bytes are small enough, else for a merge join."""
    return F.broadcast(frame) if rows * width <= BROADCAST else frame.hint("merge")


def _words(spec: ProblemSpec) -> list[Column]:
    return [F.col(w) for w in spec.names]


def _named(spec: ProblemSpec, new: list[Column], h: Column, kind: int) -> list[Column]:
    source = [F.col(w).alias(s) for w, s in zip(spec.names, spec.source_names, strict=True)]
    return [*source, *[x.alias(w) for x, w in zip(new, spec.names, strict=True)], h.alias("h"), F.lit(kind).alias("kind")]


def _signed(spec: ProblemSpec, h: Column, extra: Column | None = None) -> Column:
    odd = bits.overlap(_words(spec), [F.col(f"par_{w}") for w in spec.names])
    odd = odd + extra if extra is not None else odd
    return F.when(odd % 2 == 0, h).otherwise(-h)


def _context(h: Column, ctx: Column, occ: Column, kind: str) -> Column:
    return F.aggregate(occ, h, lambda acc, k: (acc + F.get(ctx, k)).cast(kind))


def diagonal(space: DataFrame, t: Tables) -> DataFrame:
    """Edges of each source to itself.  The values per orbital and pair are one small row that every task gets."""
    spec, m, kind = t.spec, t.spec.m, t.value_type
    zero = F.lit(0).cast(kind)
    row = space.sparkSession.createDataFrame([(t.diag1.tolist(), t.diag2.ravel().tolist())], f"d1 array<{kind}>, d2 array<{kind}>")
    with_occ = require(space, spec.names).select(*spec.names).withColumn("occ", bits.occupied(_words(spec), m)).join(F.broadcast(row))
    pairs = lambda p: F.aggregate("occ", zero, lambda acc, q: F.when(q < p, acc + F.get("d2", p * m + q)).otherwise(acc).cast(kind))
    value = F.aggregate("occ", zero, lambda acc, p: (acc + F.get("d1", p) + pairs(p)).cast(kind))
    shift = F.lit(t.shift).cast(kind)
    return with_occ.select(*_named(spec, _words(spec), value + shift, 0))


def by_join(space: DataFrame, t: Tables, kinds: tuple[int, ...] = (0, 1, 2), eps: float = 0.0) -> DataFrame:
    """Occupied orbitals and pairs, joined with the sparse tables.

    The tables depend on the orbitals and not on the data, but grow with their fourth power: up to ``BROADCAST`` bytes they
    are broadcast, beyond that pairs and moves meet in a shuffle by orbital pair.
    """
    spec, spark = t.spec, space.sparkSession
    base = require(space, spec.names).select(*spec.names)
    occ = bits.occupied(_words(spec), spec.m)
    flips = [F.col(f"flip_{w}") for w in spec.names]
    parts = []
    if 0 in kinds:
        parts.append(diagonal(base, t))
    if 1 in kinds:
        ones = base.withColumn("occ", occ).withColumn("p", F.explode("occ")).join(_sent(t.single_frame(spark), len(t.single["h"]), 32 + 8 * spec.m + 16 * spec.words), "p")
        ones = ones.where(bits.overlap(_words(spec), flips) == 1).withColumn("_v", _context(F.col("h"), F.col("ctx"), F.col("occ"), t.value_type))
        parts.append(ones.where(F.abs("_v") > eps).select(*_named(spec, bits.flip(_words(spec), flips), _signed(spec, F.col("_v")), 1)))
    if 2 in kinds:
        pairs = F.flatten(F.transform(occ, lambda p: F.transform(F.filter(occ, lambda q: q > p), lambda q: F.struct(p.alias("p"), q.alias("q")))))
        twos = base.withColumn("_pq", F.explode(pairs)).select(*spec.names, "_pq.p", "_pq.q").join(_sent(t.double_frame(spark), len(t.double["h"]), 48 + 16 * spec.words), ["p", "q"])
        twos = twos.where((bits.overlap(_words(spec), flips) == 2) & (F.abs("h") > eps))
        parts.append(twos.select(*_named(spec, bits.flip(_words(spec), flips), _signed(spec, F.col("h"), F.col("sgn0")), 2)))
    return reduce(DataFrame.unionByName, parts)


def virtual(space: DataFrame, t: Tables, eps: float = 0.0) -> DataFrame:
    """Every index of the padded lists: decompose it, read the entry, screen, flip.

    Index v of a source is pair ``v div length`` and slot ``v % length``; fillers and occupied targets drop out.
    """
    spec, spark, n = t.spec, space.sparkSession, t.spec.n
    one, two, max1, max2 = padded(t, spark)
    base = require(space, spec.names).select(*spec.names).withColumn("occ", bits.occupied(_words(spec), spec.m))
    parts = [diagonal(space, t)]
    if n and max1:
        v = base.withColumn("v", F.explode(F.sequence(F.lit(0), F.lit(n * max1 - 1)))).withColumn("p", F.get("occ", F.expr(f"int(v div {max1})")))
        hit = v.join(_sent(one, spec.m * max1, 32 + 8 * spec.m + 16 * spec.words), "p").withColumn("e", F.get("targets", F.col("v") % max1)).where("e.a is not null").select(*spec.names, "occ", "e.*")
        flips = [F.col(f"flip_{w}") for w in spec.names]
        hit = hit.where(bits.overlap(_words(spec), flips) == 1).withColumn("_v", _context(F.col("h"), F.col("ctx"), F.col("occ"), t.value_type))
        parts.append(hit.where(F.abs("_v") > eps).select(*_named(spec, bits.flip(_words(spec), flips), _signed(spec, F.col("_v")), 1)))
    if n > 1 and max2:
        ranks = F.array(*[F.struct(F.lit(r).alias("r"), F.lit(s).alias("s")) for r in range(n) for s in range(r + 1, n)])
        total = n * (n - 1) // 2 * max2
        v = base.withColumn("v", F.explode(F.sequence(F.lit(0), F.lit(total - 1)))).withColumn("_rs", F.get(ranks, F.expr(f"int(v div {max2})")))
        v = v.select(*spec.names, (F.col("v") % max2).alias("slot"), F.get("occ", F.col("_rs.r")).alias("p"), F.get("occ", F.col("_rs.s")).alias("q"))
        hit = v.join(_sent(two, spec.m * (spec.m - 1) // 2 * max2, 48 + 16 * spec.words), ["p", "q"]).withColumn("e", F.get("targets", "slot")).where("e.a is not null").select(*spec.names, "e.*")
        flips = [F.col(f"flip_{w}") for w in spec.names]
        hit = hit.where((bits.overlap(_words(spec), flips) == 2) & (F.abs("h") > eps))
        parts.append(hit.select(*_named(spec, bits.flip(_words(spec), flips), _signed(spec, F.col("h"), F.col("sgn0")), 2)))
    return reduce(DataFrame.unionByName, parts)


def _ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[0] .. starts[0]+counts[0]-1, starts[1] .. , one after the other."""
    ends = np.cumsum(counts)
    return np.repeat(starts - (ends - counts), counts) + np.arange(int(ends[-1]) if len(ends) else 0)


def edge_block(words: np.ndarray, t: Tables, eps: float, index: dict) -> tuple[np.ndarray, ...]:
    """All edges of a block of sources: (source row, target words, value, kind).  Survivors are compacted by one mask."""
    m, n = t.spec.m, t.spec.n
    occ = bits.occupied_rows(words, m, n)
    rows, new, value, kind = [np.arange(len(words))], [words], [], [np.zeros(len(words), np.int32)]
    pair = t.diag2[occ[:, :, None], occ[:, None, :]].sum((1, 2)) / 2
    value.append(t.diag1[occ].sum(1) + pair + t.shift)
    one, two = t.single, t.double
    start, count = index["one"]
    r = np.repeat(np.arange(len(words)), n)
    e = _ranges(start[occ.ravel()], count[occ.ravel()])
    s = np.repeat(r, count[occ.ravel()])
    free = np.bitwise_count(words[s] & one["flip"][e]).sum(1) == 1
    s, e = s[free], e[free]
    v = one["h"][e] + np.take_along_axis(one["ctx"][e], occ[s], 1).sum(1)
    keep = np.abs(v) > eps
    s, e, v = s[keep], e[keep], v[keep]
    odd = bits.parity(words[s] & one["parity"][e])
    rows.append(s)
    new.append(words[s] ^ one["flip"][e])
    value.append(np.where(odd == 0, v, -v))
    kind.append(np.ones(len(s), np.int32))
    i, j = np.triu_indices(n, 1)
    start, count = index["two"]
    code = (occ[:, i] * m + occ[:, j]).ravel()
    e = _ranges(start[code], count[code])
    s = np.repeat(np.repeat(np.arange(len(words)), len(i)), count[code])
    keep = (np.bitwise_count(words[s] & two["flip"][e]).sum(1) == 2) & (np.abs(two["h"][e]) > eps)
    s, e = s[keep], e[keep]
    odd = bits.parity(words[s] & two["parity"][e]) ^ two["sgn0"][e]
    rows.append(s)
    new.append(words[s] ^ two["flip"][e])
    value.append(np.where(odd == 0, two["h"][e], -two["h"][e]))
    kind.append(np.full(len(s), 2, np.int32))
    return tuple(np.concatenate(x) for x in (rows, new, value, kind))


def table_index(t: Tables) -> dict:
    """Where the entries of each orbital and pair lie; sorts the tables that way."""
    m = t.spec.m
    for table, key in ((t.single, t.single["p"]), (t.double, t.double["p"] * m + t.double["q"])):
        order = np.argsort(key, kind="stable")
        for c in table:
            table[c] = table[c][order]
    out = {}
    for name, key, size in (("one", t.single["p"], m), ("two", t.double["p"] * m + t.double["q"], m * m)):
        count = np.bincount(key, minlength=size)
        out[name] = np.cumsum(count) - count, count
    return out


def by_batch(space: DataFrame, t: Tables, eps: float = 0.0, block: int = 256) -> DataFrame:
    """The same in vectorised blocks of ``block`` sources inside each task."""
    spec = t.spec
    held = space.sparkSession.sparkContext.broadcast((t, table_index(t)))
    schema = edge_schema(spec, T.LongType() if t.exact else T.DoubleType())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables, index = held.value
        for batch in batches:
            words = np.stack([c.to_numpy() for c in batch.columns], 1)
            for at in range(0, len(words), block):
                part = words[at : at + block]
                rows, new, value, kind = edge_block(part, tables, eps, index)
                source = part[rows]
                value = value.astype(np.int64) if tables.exact else value
                columns = [np.ascontiguousarray(x[:, k]) for x in (source, new) for k in range(x.shape[1])]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (*columns, value, kind)], schema.names)

    return require(space, spec.names).select(*spec.names).mapInArrow(run, schema)


def moves(space: DataFrame, spec: ProblemSpec, kinds: tuple[int, ...] = (1, 2), source: bool = False) -> DataFrame:
    """Targets of all one- and two-particle moves without a Hamiltonian: occupied (pair) masks times empty (pair) masks.

    Two arrays of masks per source, two explodes and an exclusive or; all of it in the JVM and without any table.
    """
    m = spec.m
    base = require(space, spec.names).select(*spec.names)
    names = spec.names

    def masks(orbitals: Column, size: int) -> Column:
        single = lambda p: F.struct(*[F.when((p >= k * 63) & (p < (k + 1) * 63), F.call_function("shiftleft", F.lit(1).cast("long"), (p - k * 63).cast("int"))).otherwise(F.lit(0).cast("long")).alias(w) for k, w in enumerate(names)])
        ones = F.transform(orbitals, single)
        if size == 1:
            return ones
        both = lambda x, y: F.struct(*[x[w].bitwiseOR(y[w]).alias(w) for w in names])
        return F.flatten(F.transform(ones, lambda x, i: F.transform(F.slice(ones, i + 2, F.greatest(F.size(ones) - i - 1, F.lit(0))), lambda y: both(x, y))))

    parts = []
    for kind in kinds:
        at = base.withColumn("_o", F.explode(masks(bits.occupied(_words(spec), m), kind)))
        at = at.withColumn("_v", F.explode(masks(bits.virtual(_words(spec), m), kind)))
        new = [F.col(w).bitwiseXOR(F.col("_o")[w]).bitwiseXOR(F.col("_v")[w]) for w in names]
        if source:
            parts.append(at.select(*_named(spec, new, F.lit(1).cast("long"), kind)))
        else:
            parts.append(at.select(*[x.alias(w) for x, w in zip(new, names, strict=True)]))
    return reduce(DataFrame.unionByName, parts)


def within(space: DataFrame, targets: DataFrame, t: Tables, eps: float = 0.0) -> DataFrame:
    """Edges whose target is in ``targets``: generation and a semi join, in place of comparing all pairs."""
    return by_join(space, t, eps=eps).join(targets.select(*t.spec.names), t.spec.names, "left_semi")
