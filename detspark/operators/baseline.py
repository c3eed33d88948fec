"""Baselines: central and hashed duplicate removal, row-by-row generation, and comparing all pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.functions.schema import BITS, edge_schema
from detspark.operators.dedup import key_names
from detspark.operators.excite import Tables

#: the central root holds all rows; beyond this the baseline refuses
ROOT_ROWS = 200_000_000
#: edges that row-wise generation holds before it passes them on
FLUSH = 50_000


def dedup_central(frame: DataFrame, parts: int, limit: int = ROOT_ROWS) -> DataFrame:
    """All keys to one partition, distinct there, then dealt out again."""
    names = key_names(frame)
    if frame.select(*names).limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} rows for the root")
    return frame.select(*names).repartition(1).dropDuplicates(names).repartition(parts)


def dedup_hash(frame: DataFrame, parts: int | None = None) -> DataFrame:
    """Distinct by hash: partial aggregate, hash shuffle, final aggregate."""
    names = key_names(frame)
    keys = frame.select(*names)
    return (keys.repartition(parts, *names) if parts else keys).dropDuplicates(names)


def dedup_salted(frame: DataFrame, parts: int, salts: int = 8) -> DataFrame:
    """Distinct by key and salt, then by key: a frequent key is spread over ``salts`` tasks at the cost of a second shuffle."""
    names = key_names(frame)
    salted = frame.select(*names, F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(salts)).alias("salt"))
    once = salted.repartition(parts, *names, "salt").dropDuplicates([*names, "salt"])
    return once.select(*names).repartition(parts, *names).dropDuplicates(names)


def generate_rowwise(space: DataFrame, t: Tables) -> DataFrame:
    """Coupled generation with a Python loop per source and move: what a host without vector units does."""
    from pyspark.sql import types as T

    spec = t.spec
    m, names = spec.m, spec.names
    schema = edge_schema(spec, T.LongType() if t.exact else T.DoubleType())
    one: dict[int, list] = {}
    for p, a, h, ctx in zip(*(t.single[c].tolist() for c in ("p", "a", "h", "ctx")), strict=True):
        one.setdefault(p, []).append((a, h, ctx))
    two: dict[tuple[int, int], list] = {}
    for p, q, a, b, h in zip(*(t.double[c].tolist() for c in "pqabh"), strict=True):
        two.setdefault((p, q), []).append((a, b, 1 << a | 1 << b, h))
    held = space.sparkSession.sparkContext.broadcast((one, two, t.diag1.tolist(), t.diag2.tolist(), int(t.shift) if t.exact else float(t.shift)))
    gap = [[((1 << max(p, a)) - 1) & ~((1 << (min(p, a) + 1)) - 1) for a in range(m)] for p in range(m)]  # the orbitals strictly between

    def edges(word: int) -> Iterator[tuple]:
        one, two, d1, d2, shift = held.value
        occ = [p for p in range(m) if word >> p & 1]
        yield word, sum(d1[p] for p in occ) + sum(d2[p][q] for i, p in enumerate(occ) for q in occ[i + 1 :]) + shift, 0
        for p in occ:
            for a, h, ctx in one.get(p, ()):
                if not word >> a & 1:
                    v = h + sum([ctx[k] for k in occ])
                    if v:
                        yield word ^ 1 << p ^ 1 << a, -v if (word & gap[p][a]).bit_count() & 1 else v, 1
        for i, p in enumerate(occ):
            for q in occ[i + 1 :]:
                for a, b, both, h in two.get((p, q), ()):
                    if not word & both:
                        mid = word ^ 1 << p ^ 1 << a
                        crossed = (word & gap[p][a]).bit_count() + (mid & gap[q][b]).bit_count()
                        yield mid ^ 1 << q ^ 1 << b, -h if crossed & 1 else h, 2

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shifts, low = [BITS * k for k in range(spec.words)], (1 << BITS) - 1
        for frame in frames:
            rows: list[tuple] = []
            for words in frame.itertuples(index=False, name=None):
                rows += [(*words, *[new >> k & low for k in shifts], v, kind) for new, v, kind in edges(sum(w << k for w, k in zip(words, shifts, strict=True)))]
                if len(rows) >= FLUSH:
                    yield pd.DataFrame(rows, columns=schema.names)
                    rows = []
            yield pd.DataFrame(rows, columns=schema.names)

    return space.select(*names).mapInPandas(run, schema)


def couple_allpairs(space: DataFrame, full: DataFrame, t: Tables) -> DataFrame:
    """Pairs that differ in at most four bits, by comparing each source with each configuration: the brute-force check."""
    spec = t.spec
    source = space.select(*[F.col(w).alias(s) for w, s in zip(spec.names, spec.source_names, strict=True)])
    far = sum((F.bit_count(F.col(s).bitwiseXOR(F.col(w))) for w, s in zip(spec.names, spec.source_names, strict=True)), F.lit(0))
    return source.join(full.select(*spec.names), far <= 4).withColumn("kind", (far / 2).cast("int"))


def in_core(words: np.ndarray, t: Tables) -> tuple[int, int, int]:
    """Single pass without batches: (edges, unique keys, bytes held at once), everything in memory."""
    from detspark.operators.dedup import unique_rows
    from detspark.operators.generate import edge_block, table_index

    rows, new, value, kind = edge_block(words, t, 0.0, table_index(t))
    unique = unique_rows(new)
    return len(rows), len(unique), rows.nbytes + new.nbytes + value.nbytes + kind.nbytes + unique.nbytes + 8 * len(rows)
