"""Local and global energies from edges and amplitudes.

Amplitudes are ``psi`` (real; whole numbers in exact mode) or ``re, im``.  Sums avoid dividing by an amplitude: the energy is
sum of psi_i * num_i over sum of psi_i², where num_i is the sum of h * psi over the edges of i.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detspark.functions.schema import ProblemSpec
from detspark.operators import generate
from detspark.operators.excite import Tables

_EXACT = "decimal(38,0)"


def complex_amps(amps: DataFrame) -> DataFrame:
    """``log_abs, phase`` as ``re, im``, scaled by the largest modulus; energies don't depend on the scale."""
    top = amps.agg(F.max("log_abs")).first()[0] or 0.0
    size = F.exp(F.col("log_abs") - F.lit(top))
    keep = [c for c in amps.columns if c not in ("log_abs", "phase")]
    return amps.select(*keep, (size * F.cos("phase")).alias("re"), (size * F.sin("phase")).alias("im"))


def local(edges: DataFrame, amps: DataFrame, spec: ProblemSpec, joined: bool = False) -> DataFrame:
    """Per source: numerator, own amplitude, weight and local energy (null where the amplitude is 0).

    One join by target key and one grouped sum by source, with partial sums before the shuffle.  ``joined``: edges already
    carry amplitudes.
    """
    real = "psi" in amps.columns
    values = ["psi"] if real else ["re", "im"]
    full = edges if joined else edges.join(amps.select(*spec.names, *values), spec.names)
    exact = real and dict(full.dtypes)["h"] == "bigint" and dict(full.dtypes)["psi"] == "bigint"
    cast = lambda c: F.col(c).cast(_EXACT if exact else "double")
    sums = full.groupBy(*spec.source_names).agg(*[F.sum((cast("h") * cast(v)).cast(_EXACT) if exact else cast("h") * cast(v)).alias(f"num_{v}") for v in values])
    own = amps.select(*[F.col(w).alias(s) for w, s in zip(spec.names, spec.source_names, strict=True)], *values)
    out = sums.join(own, spec.source_names)
    if real:
        eloc = F.when(F.col("psi") != 0, F.col("num_psi").cast("double") / F.col("psi").cast("double"))
        return out.select(*spec.source_names, F.col("num_psi").alias("num_re"), F.col("psi").alias("psi_re"), (cast("psi") * cast("psi")).alias("wgt"), eloc.alias("eloc_re"))
    wgt = F.col("re") * F.col("re") + F.col("im") * F.col("im")
    er = F.when(wgt > 0, (F.col("num_re") * F.col("re") + F.col("num_im") * F.col("im")) / wgt)
    ei = F.when(wgt > 0, (F.col("num_im") * F.col("re") - F.col("num_re") * F.col("im")) / wgt)
    return out.select(*spec.source_names, "num_re", "num_im", F.col("re").alias("psi_re"), F.col("im").alias("psi_im"), wgt.alias("wgt"), er.alias("eloc_re"), ei.alias("eloc_im"))


def total(rows: DataFrame) -> DataFrame:
    """One row ``num, norm, energy, variance, n`` of local energies; whole-number input is summed exactly, in any order."""
    complex_ = "psi_im" in rows.columns
    exact = dict(rows.dtypes)["num_re"].startswith("decimal")
    wide: Column = F.col("psi_re").cast(_EXACT) * F.col("num_re") if exact else F.col("psi_re") * F.col("num_re")
    part = wide.cast(_EXACT) if exact else wide
    if complex_:
        part = part + F.col("psi_im") * F.col("num_im")
    sums = rows.agg(F.sum(part).alias("num"), F.sum("wgt").alias("norm"), F.sum(F.col("wgt").cast("double") * F.col("eloc_re") * F.col("eloc_re")).alias("_sq"), F.count("*").alias("n"))
    energy = F.when(F.col("norm") != 0, F.col("num").cast("double") / F.col("norm").cast("double"))
    return sums.withColumn("energy", energy).select("num", "norm", "energy", F.greatest(F.coalesce(F.col("_sq") / F.col("norm").cast("double") - F.col("energy") * F.col("energy"), F.lit(0.0)), F.lit(0.0)).alias("variance"), "n")


def energy(space: DataFrame, t: Tables, amps: DataFrame, form: str = "mixed", eps: float = 0.0, edges: DataFrame | None = None) -> DataFrame:
    """Global energy of ``space``.  ``mixed``: targets run over all coupled configurations.  ``variational``: targets stay inside
    ``space``, a true upper bound.  Without ``edges`` they are generated anew, which costs less than storing them.
    """
    spec = t.spec
    edges = generate.by_join(space, t, eps=eps) if edges is None else edges
    if form == "variational":
        edges = edges.join(space.select(*spec.names), spec.names, "left_semi")
    return total(local(edges, amps, spec))
