"""Exact answers: dense diagonalisation, distributed Lanczos, and diagonalisation in a selected space."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.functions.schema import ProblemSpec
from detspark.operators import generate
from detspark.operators.excite import Tables
from detspark.operators.space import enumerate_space, unrank
from detspark.plans.scratch import staged

#: largest matrix that is built on the driver
DENSE_LIMIT = 5000


def dense_matrix(t: Tables, words: np.ndarray) -> np.ndarray:
    """The matrix over the given configurations, from the tables."""
    if len(words) > DENSE_LIMIT:
        raise ValueError(f"{len(words)} rows are too many for a dense matrix")
    keys = {tuple(w): i for i, w in enumerate(words.tolist())}
    rows, new, value, _ = generate.edge_block(words, t, -1.0, generate.table_index(t))
    out = np.zeros((len(words),) * 2)
    for r, w, v in zip(rows.tolist(), new.tolist(), value.tolist(), strict=True):
        if (c := keys.get(tuple(w))) is not None:
            out[r, c] += v
    return out


def all_words(spec: ProblemSpec) -> np.ndarray:
    from math import comb

    return unrank(np.arange(comb(spec.m, spec.n)), spec.m, spec.n)


def dense_ground(t: Tables) -> tuple[float, np.ndarray, np.ndarray]:
    """(lowest value, its vector, configurations) of the full space."""
    words = all_words(t.spec)
    values, vectors = np.linalg.eigh(dense_matrix(t, words))
    return float(values[0]), vectors[:, 0], words


def selected_ground(space: DataFrame, t: Tables) -> float:
    """Lowest value inside a selected space of at most ``DENSE_LIMIT`` configurations."""
    rows = space.select(*t.spec.names).limit(DENSE_LIMIT + 1).collect()
    return float(np.linalg.eigvalsh(dense_matrix(t, np.array([tuple(r) for r in rows], np.int64)))[0])


def matvec(edges: DataFrame, vector: DataFrame, spec: ProblemSpec) -> DataFrame:
    """``vector`` (words, x) times the matrix that ``edges`` hold: (words, x)."""
    joined = edges.join(vector, spec.names)
    sums = joined.groupBy(*spec.source_names).agg(F.sum(F.col("h") * F.col("x")).alias("x"))
    return sums.select(*[F.col(s).alias(w) for s, w in zip(spec.source_names, spec.names, strict=True)], "x")


def lanczos(t: Tables, space: DataFrame, steps: int = 30, tol: float = 1e-9) -> float:
    """Lowest value over ``space`` by a three-term recurrence; per step one join and one grouped sum, two numbers to the driver."""
    spec = t.spec
    edges = staged(generate.within(space, space, t, eps=0.0), "edges")
    names = spec.names
    start = F.pmod(F.xxhash64(*names), F.lit(1000)) / 1000.0 + 0.5
    v = staged(space.select(*names, start.cast("double").alias("x")), "vector")
    norm = float(v.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0])
    v = v.withColumn("x", F.col("x") / norm)
    before, beta, alphas, betas, last = None, 0.0, [], [], None
    for _ in range(steps):
        w = matvec(edges, v, spec)
        joined = v.join(w.withColumnRenamed("x", "y"), names, "left").select(*names, "x", F.coalesce("y", F.lit(0.0)).alias("y"))
        if before is not None:
            joined = joined.join(before.withColumnRenamed("x", "z"), names).withColumn("y", F.col("y") - beta * F.col("z")).drop("z")
        joined = staged(joined, "vector")
        alpha = float(joined.agg(F.sum(F.col("x") * F.col("y"))).first()[0])
        new = joined.select(*names, (F.col("y") - alpha * F.col("x")).alias("x"))
        alphas.append(alpha)
        tri = np.diag(alphas) + np.diag(betas, 1) + np.diag(betas, -1)
        value = float(np.linalg.eigvalsh(tri)[0])
        beta = float(new.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0])
        if beta < 1e-10 or (last is not None and abs(value - last) < tol):
            return value
        last = value
        betas.append(beta)
        before, v = joined.select(*names, "x"), new.withColumn("x", F.col("x") / beta)
    return last


def full_space(spark, t: Tables) -> DataFrame:
    return enumerate_space(spark, t.spec)
