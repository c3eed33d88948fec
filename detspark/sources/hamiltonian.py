"""Hamiltonians: textbook models and an integer one made from the given tables.

Two-body values are in chemists' order, (pq|rs) = the repulsion of the densities p*q and r*s, over spin orbitals.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from detspark.functions.schema import ProblemSpec
from detspark.sources.tables import brand_ranks, load


@dataclass(frozen=True)
class Hamiltonian:
    """One-body matrix and a vectorised two-body function; ``exact`` means whole numbers."""

    spec: ProblemSpec
    h1: np.ndarray
    pair: Callable[..., np.ndarray]
    shift: float = 0.0
    exact: bool = False
    name: str = ""

    @property
    def value_type(self) -> str:
        return "long" if self.exact else "double"

    def anti(self, p, q, a, b) -> np.ndarray:
        """Direct minus exchange value of moving p to a and q to b."""
        return self.pair(p, a, q, b) - self.pair(p, b, q, a)

    def frames(self, spark: SparkSession) -> tuple[DataFrame, DataFrame]:
        """``h1(p,q,v)`` and ``h2(p,q,r,s,v)`` without zeros; for small ``m``."""
        m, cast = self.spec.m, int if self.exact else float
        one = [(int(p), int(q), cast(self.h1[p, q])) for p, q in np.argwhere(self.h1 != 0)]
        index = np.indices((m,) * 4).reshape(4, -1)
        value = self.pair(*index)
        two = [(*(int(x) for x in index[:, k]), cast(value[k])) for k in np.flatnonzero(value)]
        kind = self.value_type
        return spark.createDataFrame(one, f"p int, q int, v {kind}"), spark.createDataFrame(two, f"p int, q int, r int, s int, v {kind}")


def dense(spec: ProblemSpec, h1: np.ndarray, g: np.ndarray, **more) -> Hamiltonian:
    return Hamiltonian(spec, h1, lambda p, q, r, s: g[p, q, r, s], **more)


def _with_spin(h: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spin orbitals 2 * place + spin from places."""
    k = 2 * len(h)
    place, spin = np.arange(k) // 2, np.arange(k) % 2
    same = (spin[:, None] == spin[None, :]).astype(float)
    h_spin = h[np.ix_(place, place)] * same
    return h_spin, g[np.ix_(place, place, place, place)] * same[:, :, None, None] * same[None, None, :, :]


def two_level_molecule() -> Hamiltonian:
    """The hydrogen molecule in a minimal basis at 1.401 atomic units (fixed textbook integrals)."""
    h = np.diag([-1.252477, -0.475934])
    g = np.zeros((2, 2, 2, 2))
    g[0, 0, 0, 0], g[1, 1, 1, 1] = 0.674493, 0.697397
    g[0, 0, 1, 1] = g[1, 1, 0, 0] = 0.663472
    g[0, 1, 0, 1] = g[0, 1, 1, 0] = g[1, 0, 0, 1] = g[1, 0, 1, 0] = 0.181287
    return dense(ProblemSpec(4, 2), *_with_spin(h, g), shift=1 / 1.401, name="two_level_molecule")


def lattice(sites: int, particles: int, t: float = 1.0, u: float = 4.0, ring: bool = True) -> Hamiltonian:
    """Hopping ``t`` between neighbours, repulsion ``u`` of two on a site."""
    h = np.zeros((sites, sites))
    for i in range(sites - (0 if ring and sites > 2 else 1)):
        h[i, (i + 1) % sites] = h[(i + 1) % sites, i] = -t
    g = np.zeros((sites,) * 4)
    for i in range(sites):
        g[i, i, i, i] = u
    return dense(ProblemSpec(2 * sites, particles), *_with_spin(h, g), name=f"lattice{sites}{'_ring' if ring and sites > 2 else ''}")


def table(spark: SparkSession, sf_dir: str, m: int, n: int, orbital: str = "brand", band: int | None = None, spacing: int = 0) -> Hamiltonian:
    """Whole-number Hamiltonian from line items.

    Lines belong to the orbital of their part (rank of its brand, or part key modulo ``m``).  For each return flag the
    number of orders that hold both orbitals p and q gives a factor matrix of small integers; their products are the
    two-body values, the sums over flags the one-body ones.  Counting is distributed; at most 3 m² counts come back.
    """
    return from_counts(pair_counts(spark, sf_dir, m, orbital), m, n, band, spacing)


def pair_counts(spark: SparkSession, sf_dir: str, m: int, orbital: str = "brand") -> np.ndarray:
    """Per return flag the orders that hold both orbitals p and q, for the first ``m`` orbitals: what ``table`` counts."""
    part, lines = load(spark, sf_dir, "part"), load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_returnflag")
    if orbital == "brand":
        marked = lines.join(brand_ranks(part), F.col("l_partkey") == F.col("p_partkey"))
    else:
        marked = lines.withColumn("o", F.pmod("l_partkey", F.lit(m)).cast("int"))
    held = marked.where(F.col("o") < m).groupBy("l_returnflag", "l_orderkey").agg(F.collect_set("o").alias("os"))
    both = held.select("l_returnflag", F.explode("os").alias("p"), "os").select("l_returnflag", "p", F.explode("os").alias("q"))
    counts = both.groupBy("l_returnflag", "p", "q").count().collect()
    flags = sorted({r["l_returnflag"] for r in counts})
    c = np.zeros((len(flags), m, m), np.int64)
    for r in counts:
        c[flags.index(r["l_returnflag"]), r["p"], r["q"]] = r["count"]
    return c


def from_counts(c: np.ndarray, m: int, n: int, band: int | None = None, spacing: int = 0) -> Hamiltonian:
    """``table`` from counts of ``m`` orbitals or, as ranks of brands don't depend on ``m``, of more; flags without any drop out."""
    c = c[:, :m, :m]
    c = c[c.any((1, 2))]
    factor = c % 7 - 3
    if band is not None:
        p = np.arange(m)
        factor[:, np.abs(p[:, None] - p[None, :]) > band] = 0
    total = c.sum(0)
    h1 = -(total % 11)
    np.fill_diagonal(h1, -(np.diag(total) % 101) + spacing * np.arange(m))

    def pair(p, q, r, s):
        return sum(f[p, q] * f[r, s] for f in factor)

    return Hamiltonian(ProblemSpec(m, n), h1, pair, exact=True, name=f"table_m{m}_n{n}")


def from_integrals(rows: DataFrame, spec: ProblemSpec) -> Hamiltonian:
    """From a parsed integral file over places (``sources.tables.read_integrals``), with its eightfold symmetry; for small bases."""
    k = spec.m // 2
    h, g, shift = np.zeros((k, k)), np.zeros((k,) * 4), 0.0
    for r in rows.collect():  # a table of O(m^4) entries: a parameter of the problem
        p, q, a, b, v = r["p"] - 1, r["q"] - 1, r["r"] - 1, r["s"] - 1, r["v"]
        if a >= 0:
            for x, y, z, w in ((p, q, a, b), (q, p, a, b), (p, q, b, a), (q, p, b, a)):
                g[x, y, z, w] = g[z, w, x, y] = v
        elif q >= 0:
            h[p, q] = h[q, p] = v
        elif p < 0:
            shift = v
    return dense(spec, *_with_spin(h, g), shift=shift, name="integrals")


def orbital_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Brand of each orbital, for reading results."""
    part = load(spark, sf_dir, "part").select("p_brand").distinct()
    return part.withColumn("orbital", F.dense_rank().over(Window.orderBy("p_brand")) - 1)
