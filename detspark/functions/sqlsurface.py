"""The methods as SQL functions and views."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.functions import bits
from detspark.functions.ansatz import Model
from detspark.functions.schema import ProblemSpec
from detspark.operators.excite import Tables
from detspark.operators.generate import edge_block, table_index


def register(spark: SparkSession, t: Tables, model: Model | None = None) -> None:
    """Register for one-word problems: ``config_parse``, ``config_show``, the table function ``couple(w)`` and ``log_psi(w)``.

    ``couple`` is for ``LATERAL`` in SQL; the DataFrame forms are faster.
    """
    spec = t.spec
    if spec.words != 1:
        raise ValueError("the SQL functions take one-word configurations")
    spark.sql(f"create or replace temporary function config_parse(s string) returns bigint return cast(conv(s, 2, 10) as bigint)")
    spark.sql(f"create or replace temporary function config_show(w bigint) returns string return lpad(bin(w), {spec.m}, '0')")
    index = table_index(t)

    class Couple:
        def eval(self, w: int):
            _, new, value, kind = edge_block(np.array([[w]], np.int64), t, 0.0, index)
            for x, v, k in zip(new[:, 0].tolist(), value.tolist(), kind.tolist(), strict=True):
                yield x, float(v), k

    spark.udtf.register("couple", F.udtf(Couple, returnType="w0 bigint, h double, kind int"))
    if model is not None:

        @F.pandas_udf(T.DoubleType())
        def log_psi(w: pd.Series) -> pd.Series:
            return pd.Series(model.forward(bits.to_bits(w.to_numpy(np.int64)[:, None], spec.m))[0])

        spark.udf.register("log_psi", log_psi)


def views(spark: SparkSession, spec: ProblemSpec, **frames: DataFrame) -> None:
    """Temporary views of a run's tables (space, coupled, unique_set, amps, …)."""
    for name, frame in frames.items():
        frame.createOrReplaceTempView(name)


def table_views(spark: SparkSession, t: Tables) -> None:
    t.single_frame(spark).createOrReplaceTempView("t_single")
    t.double_frame(spark).createOrReplaceTempView("t_double")
