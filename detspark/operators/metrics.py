"""Cost and accuracy measures."""

from __future__ import annotations

import time
from contextlib import contextmanager
from math import comb

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from detspark.operators.dedup import key_names


def balance(counts: DataFrame, column: str, *by: str) -> DataFrame:
    """Largest, smallest, their ratio (null if the smallest is 0), mean, population deviation and coefficient of variation of counts per part."""
    c = F.col(column).cast("double")
    out = counts.groupBy(*by).agg(F.max(c).alias("max"), F.min(c).alias("min"), F.avg(c).alias("mean"), F.stddev_pop(c).alias("std"))
    return out.withColumn("ratio", F.when(F.col("min") > 0, F.col("max") / F.col("min"))).withColumn("cv", F.when(F.col("mean") > 0, F.col("std") / F.col("mean")))


def partition_balance(frame: DataFrame, parts: int) -> DataFrame:
    """``balance`` of the rows of each partition, empty ones counted as 0."""
    rows = frame.groupBy(F.spark_partition_id().alias("part")).count()
    return balance(frame.sparkSession.range(parts).select(F.col("id").cast("int").alias("part")).join(rows, "part", "left").na.fill(0), "count")


def throughput(items: int, seconds: float) -> float:
    """Redundant items per second, in millions."""
    return items / seconds / 1e6 if seconds > 0 else float("nan")


def redundancy(edges: DataFrame) -> DataFrame:
    """``generated, unique, rate``."""
    names = key_names(edges)
    counts = edges.groupBy(*names).count()
    return counts.agg(F.coalesce(F.sum("count"), F.lit(0)).alias("generated"), F.count("*").alias("unique")).withColumn("rate", F.when(F.col("generated") > 0, 1 - F.col("unique") / F.col("generated")))


def growth_curve(edges: DataFrame, block: str = "block") -> DataFrame:
    """Per block the generated and unique keys up to it: a key counts where it is first seen.  One shuffle by key; the running sums run over blocks."""
    names = key_names(edges)
    first = edges.groupBy(*names).agg(F.min(block).alias(block)).groupBy(block).agg(F.count("*").alias("_u"))
    made = edges.groupBy(block).agg(F.count("*").alias("_g"))
    upto = Window.orderBy(block).rowsBetween(Window.unboundedPreceding, 0)
    both = made.join(first, block, "left").na.fill(0, ["_u"])
    return both.select(block, F.sum("_g").over(upto).alias("generated"), F.sum("_u").over(upto).alias("unique"))


def overlap_estimate(a: DataFrame, b: DataFrame) -> DataFrame:
    """Estimated common keys of two blocks from sketches, without an exchange of keys."""
    sketch = lambda f: f.agg(F.theta_sketch_agg(F.xxhash64(*key_names(f))).alias("s"))
    return sketch(a).join(sketch(b).withColumnRenamed("s", "r")).select(F.theta_sketch_estimate(F.theta_intersection("s", "r")).alias("common"))


def unique_estimate(edges: DataFrame, rsd: float = 0.02) -> DataFrame:
    """Estimated unique keys, to choose the number of parts before the exchange."""
    return edges.agg(F.approx_count_distinct(F.xxhash64(*key_names(edges)), rsd).alias("unique"))


class StageTimer:
    """Wall-clock seconds of named stages, per iteration."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, str, float]] = []

    @contextmanager
    def stage(self, iteration: int, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.rows.append((iteration, name, time.perf_counter() - began))

    def frame(self, spark: SparkSession) -> DataFrame:
        return stage_share(spark.createDataFrame(self.rows, "iter int, stage string, seconds double"))


def stage_share(times: DataFrame) -> DataFrame:
    """``iter, stage, seconds`` with the share of the iteration's time."""
    summed = times.groupBy("iter", "stage").agg(F.sum("seconds").alias("seconds"))
    return summed.withColumn("share", F.col("seconds") / F.sum("seconds").over(Window.partitionBy("iter")))


def speedup(before: DataFrame, after: DataFrame) -> DataFrame:
    """Old over new seconds by stage, and in total (stage ``all``)."""
    both = lambda f: f.groupBy("stage").agg(F.sum("seconds").alias("s")).unionByName(f.agg(F.lit("all").alias("stage"), F.sum("seconds").alias("s")))
    return both(before).join(both(after).withColumnRenamed("s", "t"), "stage").select("stage", (F.col("s") / F.col("t")).alias("speedup"))


def abs_error(history: DataFrame, reference: float) -> DataFrame:
    return history.withColumn("error", F.abs(F.col("energy") - F.lit(reference)))


def within_threshold(history: DataFrame, reference: float, tol: float = 1.6e-3) -> DataFrame:
    return abs_error(history, reference).withColumn("within", F.col("error") < tol)


def first_below(history: DataFrame, reference: float, tol: float = 1.6e-3) -> DataFrame:
    """First step whose error is under the threshold."""
    return within_threshold(history, reference, tol).where("within").agg(F.min("iter").alias("first"))


def smoothed(history: DataFrame, width: int = 5) -> DataFrame:
    """Moving mean of the energy and its change from step to step."""
    over = Window.orderBy("iter").rowsBetween(-(width - 1), 0)
    out = history.withColumn("smooth", F.avg("energy").over(over))
    return out.withColumn("slope", F.col("smooth") - F.lag("smooth").over(Window.orderBy("iter")))


def trajectory_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Mean absolute, root mean square and largest difference of two energy histories, step by step."""
    d = F.abs(F.col("energy") - F.col("_e"))
    both = a.select("iter", "energy").join(b.select("iter", F.col("energy").alias("_e")), "iter")
    return both.agg(F.avg(d).alias("mae"), F.sqrt(F.avg(d * d)).alias("rmse"), F.max(d).alias("max"))


def scaling(times: DataFrame, mode: str) -> DataFrame:
    """``(p, seconds)`` with the efficiency against the smallest p: ``strong`` T0 p0 / (T p), ``weak`` T0 / T (may exceed 1)."""
    first = Window.orderBy("p")
    t0, p0 = F.first("seconds").over(first), F.first("p").over(first)
    value = t0 * p0 / (F.col("seconds") * F.col("p")) if mode == "strong" else t0 / F.col("seconds")
    return times.withColumn("efficiency", value)


def edge_bound(m: int, n: int) -> int:
    """Moves of one source: singles and doubles."""
    return n * (m - n) + comb(n, 2) * comb(m - n, 2)


def virtual_size(n: int, max1: int, max2: int) -> tuple[int, int]:
    """Indices of the padded lists that one source visits."""
    return n * max1, comb(n, 2) * max2


def theoretical_bytes(generated: int, unique: int, words: int) -> int:
    """All edges, the reverse index and all amplitudes at once."""
    return generated * (8 * words * 2 + 8 + 1) + 8 * generated + unique * (8 * words + 16)


def staged_bytes(batch: int, words: int, weights: int, table: int, buffers: int = 2) -> int:
    """``buffers`` batches of edges, the model's weights and the tables."""
    return buffers * batch * (8 * words * 2 + 8 + 1) + weights + table


def reduction(theoretical: float, measured: float) -> float:
    return 1 - measured / theoretical
