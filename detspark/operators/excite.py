"""Excitation tables: for each move its value, the words it flips and the words whose parity gives its sign."""

from __future__ import annotations

from dataclasses import dataclass
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from detspark.functions import bits
from detspark.functions.schema import ProblemSpec
from detspark.sources.hamiltonian import Hamiltonian

#: bytes of a padded entry: two orbital numbers and a value, of 4 bytes each
ENTRY = 12


@dataclass(frozen=True)
class Tables:
    """Moves as arrays on the driver; their size depends on the orbitals and never on the data.

    single: p, a, h, ctx (m values to add for each occupied orbital), flip and parity words.
    double: p < q, a < b, h, flip and parity words, sgn0.
    """

    spec: ProblemSpec
    exact: bool
    single: dict[str, np.ndarray]
    double: dict[str, np.ndarray]
    diag1: np.ndarray
    diag2: np.ndarray
    shift: float = 0.0

    @property
    def value_type(self) -> str:
        return "long" if self.exact else "double"

    def _frame(self, spark: SparkSession, table: dict[str, np.ndarray], columns: list[str]) -> DataFrame:
        out = {c: table[c] for c in columns}
        for k, w in enumerate(self.spec.names):
            out[f"flip_{w}"], out[f"par_{w}"] = table["flip"][:, k], table["parity"][:, k]
        kinds = ", ".join(f"{c} { {'h': self.value_type, 'ctx': f'array<{self.value_type}>'}.get(c, 'int')}" for c in columns) + "".join(f", flip_{w} long, par_{w} long" for w in self.spec.names)
        return spark.createDataFrame(pd.DataFrame(out), kinds)

    def single_frame(self, spark: SparkSession) -> DataFrame:
        return self._frame(spark, self.single | {"ctx": [x.tolist() for x in self.single["ctx"]]}, ["p", "a", "h", "ctx"])

    def double_frame(self, spark: SparkSession) -> DataFrame:
        return self._frame(spark, self.double, ["p", "q", "a", "b", "h", "sgn0"])


def _cast(x: np.ndarray, exact: bool) -> np.ndarray:
    return np.asarray(x, np.int64) if exact else np.asarray(x, float)


def tables(ham: Hamiltonian, eps: float = 0.0, spin: bool = False, keep_zero: bool = False) -> Tables:
    """Tables by the rules for one- and two-particle moves.

    Doubles with \\|h\\| <= ``eps`` are left out here, as their value doesn't depend on the source.  ``spin`` also leaves out
    moves that change an orbital's parity class.  A single's value needs the other particles: ``h + sum of ctx``.
    """
    spec, m, exact = ham.spec, ham.spec.m, ham.exact
    everyone = np.arange(m)
    p, a = (x.ravel() for x in np.meshgrid(everyone, everyone, indexing="ij"))
    ok = (p != a) & ((p - a) % 2 == 0 if spin else True)
    p, a = p[ok], a[ok]
    k = everyone[None, :]
    ctx = ham.pair(p[:, None], a[:, None], k, k) - ham.pair(p[:, None], k, k, a[:, None])
    base = ham.h1[p, a]
    if not keep_zero:
        live = (base != 0) | (ctx != 0).any(1)
        p, a, ctx, base = p[live], a[live], ctx[live], base[live]
    one = np.array([bits.mask_words([i], m) for i in range(m)], np.int64)
    gap = np.array([[bits.between(i, j, m) for j in range(m)] for i in range(m)], np.int64)
    single = {"p": p, "a": a, "h": _cast(base, exact), "ctx": _cast(ctx, exact), "flip": one[p] ^ one[a], "parity": gap[p, a]}
    i, j = np.triu_indices(m, 1)
    parts = []
    for lo in range(0, len(i), max(1, 4_000_000 // max(1, len(i)))):
        hi = min(len(i), lo + max(1, 4_000_000 // max(1, len(i))))
        dp, dq = np.repeat(i[lo:hi], len(i)), np.repeat(j[lo:hi], len(i))
        da, db = np.tile(i, hi - lo), np.tile(j, hi - lo)
        ok = (dp != da) & (dp != db) & (dq != da) & (dq != db)
        if spin:
            ok &= (dp % 2 + dq % 2) == (da % 2 + db % 2)
        dp, dq, da, db = dp[ok], dq[ok], da[ok], db[ok]
        v = ham.anti(dp, dq, da, db)
        ok = np.abs(v) > eps if not keep_zero else np.ones(len(v), bool)
        parts.append((dp[ok], dq[ok], da[ok], db[ok], v[ok]))
    dp, dq, da, db, v = (np.concatenate([x[c] for x in parts]) if parts else np.zeros(0, np.int64) for c in range(5))
    second = gap[dq, db]
    double = {
        "p": dp, "q": dq, "a": da, "b": db, "h": _cast(v, exact), "flip": one[dp] ^ one[dq] ^ one[da] ^ one[db],
        "parity": gap[dp, da] ^ second, "sgn0": bits.parity((one[dp] | one[da]) & second),
    }
    diag2 = ham.pair(everyone[:, None], everyone[:, None], k, k) - ham.pair(everyone[:, None], k, k, everyone[:, None])
    return Tables(spec, exact, single, double, _cast(np.diag(ham.h1), exact), _cast(diag2, exact), ham.shift)


def padded(t: Tables, spark: SparkSession) -> tuple[DataFrame, DataFrame, int, int]:
    """Tables with rows of one length: ``(p, targets)`` and ``(p, q, targets)``, fillers with a null target and value 0.

    Returns the two tables and the two row lengths.
    """

    def lengthen(frame: DataFrame, by: list[str]) -> tuple[DataFrame, int]:
        rest = [c for c in frame.columns if c not in by]
        grouped = frame.groupBy(*by).agg(F.sort_array(F.collect_list(F.struct(*rest))).alias("targets"))
        longest = grouped.agg(F.max(F.size("targets"))).first()[0] or 0
        kind = grouped.schema["targets"].dataType.elementType
        filler = F.struct(*[(F.lit(0) if f.name == "h" else F.lit(None)).cast(f.dataType).alias(f.name) for f in kind.fields])
        return grouped.withColumn("targets", F.concat("targets", F.array_repeat(filler, F.lit(longest) - F.size("targets")))), longest

    one, max1 = lengthen(t.single_frame(spark), ["p"])
    two, max2 = lengthen(t.double_frame(spark), ["p", "q"])
    return one, two, max1, max2


def row_lengths(t: Tables) -> tuple[int, int]:
    m = t.spec.m
    one = np.bincount(t.single["p"], minlength=m)
    two = np.bincount(t.double["p"] * m + t.double["q"], minlength=m * m)
    return int(one.max(initial=0)), int(two.max(initial=0))


def footprint(t: Tables, spark: SparkSession) -> DataFrame:
    """``(bytes, pair_bytes, dense_bytes, ratio)``: padded tables over all orbitals, the pair table with a row per particle pair, and the dense matrix."""
    m, n = t.spec.m, t.spec.n
    one, two = row_lengths(t)
    size = (m * one + comb(m, 2) * two) * ENTRY
    dense = 8.0 * float(comb(m, n)) ** 2
    return spark.createDataFrame([(size, comb(n, 2) * two * ENTRY, dense, dense / max(size, 1))], "bytes long, pair_bytes long, dense_bytes double, ratio double")
