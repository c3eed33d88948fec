"""Connected components of a link table by alternating star contractions, after a local spanning forest per task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.plans.scratch import staged


def forest(left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of an edge list that are not the smallest of their component, with that smallest node."""
    if not len(left):
        return left, right
    nodes, flat = np.unique(np.concatenate([left, right]), return_inverse=True)
    a, b = flat[: len(left)], flat[len(left) :]
    parent = np.arange(len(nodes))
    while True:
        pa_, pb = parent[a], parent[b]
        low, high = np.minimum(pa_, pb), np.maximum(pa_, pb)
        live = low != high
        if not live.any():
            break
        np.minimum.at(parent, high[live], low[live])
        while True:  # flatten
            up = parent[parent]
            if (up == parent).all():
                break
            parent = up
    moved = parent != np.arange(len(nodes))
    return nodes[moved], nodes[parent[moved]]


def _shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Replace a task's links by a forest with the same components; memory follows the task's distinct nodes."""
    u, v, kept = [], [], 0
    for batch in batches:
        u.append(batch.column(0).to_numpy())
        v.append(batch.column(1).to_numpy())
        kept += batch.num_rows
        if kept > 1 << 20:
            x, y = forest(np.concatenate(u), np.concatenate(v))
            u, v, kept = [x], [y], 0
    x, y = forest(np.concatenate(u), np.concatenate(v)) if u else (np.zeros(0, np.int64),) * 2
    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["u", "v"])


def components(links: DataFrame, max_rounds: int = 64) -> DataFrame:
    """Links ``(u, v)`` (long) → ``(node, component)`` for every node that has a link; component is its smallest node.

    Each task first keeps only a spanning forest of its links.  Then large-star and small-star steps alternate until every
    node points at its smallest; both are a grouped minimum and an equi-join, so a node with very many links is split by
    the partial aggregate and by the adaptive skew join.  Self links and repeated links are allowed; an empty table gives
    an empty result.
    """
    links = links.select(F.col("u").cast("long"), F.col("v").cast("long")).where("u <> v").mapInArrow(_shrink, "u long, v long")
    edges = staged(links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "links")
    seen = None
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        small_low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(small_low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        edges = staged(small.unionByName(small_low.select("u", F.col("m").alias("v"))).distinct(), "links")
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
