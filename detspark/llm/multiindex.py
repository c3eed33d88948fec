"""Embedding near-duplicates by an inverted multi-index.

Each half of a vector has a codebook of its own; the pairs of code words form a grid of cells.  A vector lives in the cell
of its nearest code words and visits the nearest cells in the order of the summed distances, as a multi-sequence traversal
of the two sorted distance lists gives them.  How many cells are visited is fitted so that the target recall is met on the
sample and on pairs made from it.  Homes against visitors in each cell gives the pairs, which are verified in doubles.

The codebooks and the number of visits come from a sample of at most ``sample`` distinct vectors; every vector is indexed.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from detspark.llm.graph import components, forest
from detspark.llm.vectors import levelled, stacked, usable, widths
from detspark.plans.scratch import staged


@dataclass(frozen=True)
class IndexConfig:
    cosine: float = 0.95
    recall: float = 0.99
    sample: int = 4096
    per_cell: int = 32
    max_codes: int = 1024
    max_visits: int = 256
    chunk: int = 2048
    visitors: int = 8192
    seed: int = 5


def _nearest(x: np.ndarray, codes: np.ndarray) -> np.ndarray:
    return ((x * x).sum(1)[:, None] - 2 * x @ codes.T) + (codes * codes).sum(1)[None, :]


def codebook(x: np.ndarray, k: int, seed: int, rounds: int = 12) -> np.ndarray:
    """k-means code words of the rows of ``x``; empty words move to random rows."""
    rng = np.random.default_rng(seed)
    codes = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = _nearest(x, codes).argmin(1)
        count = np.bincount(near, minlength=len(codes))
        total = np.zeros_like(codes)
        np.add.at(total, near, x)
        codes = np.where(count[:, None] > 0, total / np.maximum(count, 1)[:, None], x[rng.integers(len(x), size=len(codes))])
    return codes


def traversal(x: np.ndarray, books: tuple[np.ndarray, np.ndarray], visits: int) -> np.ndarray:
    """The first ``visits`` cells of each row's multi-sequence order (cell = first code * words + second code).

    The cell at places (i, j) of the two sorted lists comes after the (i+1)(j+1)-1 cells that are no farther in both, so
    only places with (i+1)(j+1) <= visits can be among the first.
    """
    h = x.shape[1] // 2
    first, second = _nearest(x[:, :h], books[0]), _nearest(x[:, h:], books[1])
    visits = min(visits, first.shape[1] * second.shape[1])
    a, b = np.argsort(first, 1, kind="stable")[:, :visits], np.argsort(second, 1, kind="stable")[:, :visits]
    i, j = np.meshgrid(np.arange(a.shape[1]), np.arange(b.shape[1]), indexing="ij")
    at = np.flatnonzero(((i + 1) * (j + 1) <= visits).ravel())
    i, j = i.ravel()[at], j.ravel()[at]
    rows = np.arange(len(x))[:, None]
    cost = first[rows, a[:, i]] + second[rows, b[:, j]]
    order = np.argsort(cost, 1, kind="stable")[:, :visits]
    return a[rows, i[order]] * len(books[1]) + b[rows, j[order]]


def fit(sample: np.ndarray, n: int, cfg: IndexConfig) -> tuple[tuple[np.ndarray, np.ndarray], int]:
    """Codebooks for ``n`` vectors, and how many cells to visit."""
    x = levelled(sample)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    h = x.shape[1] // 2
    k = int(np.clip(np.ceil(np.sqrt(n / cfg.per_cell)), 1, cfg.max_codes))
    books = codebook(x[:, :h], k, cfg.seed), codebook(x[:, h:], k, cfg.seed + 1)
    rng = np.random.default_rng(cfg.seed)
    base = x[rng.integers(len(x), size=1024)]
    # made pairs with cosines spread from the threshold to 1, and pairs of the sample itself
    noise = rng.standard_normal(base.shape)
    noise -= (noise * base).sum(1, keepdims=True) * base
    noise /= np.maximum(np.linalg.norm(noise, axis=1, keepdims=True), 1e-12)
    c = rng.uniform(cfg.cosine, 1.0, (len(base), 1))
    left, right = [base], [c * base + np.sqrt(1 - c * c) * noise]
    close = np.argwhere(np.triu(x @ x.T >= cfg.cosine, 1))[:2048]
    left.append(x[close[:, 0]])
    right.append(x[close[:, 1]])
    a, b = np.concatenate(left), np.concatenate(right)
    path_a, path_b = traversal(a, books, cfg.max_visits), traversal(b, books, cfg.max_visits)

    def place(path: np.ndarray, home: np.ndarray) -> np.ndarray:
        hit = path == home[:, None]
        return np.where(hit.any(1), hit.argmax(1), cfg.max_visits)

    needed = np.minimum(place(path_a, path_b[:, 0]), place(path_b, path_a[:, 0])) + 1
    visits = int(np.quantile(needed, cfg.recall, method="higher"))
    return books, max(1, min(visits, path_a.shape[1]))


def _located(classes: DataFrame, books, visits: int, d: int) -> DataFrame:
    """``(cid, n, v)`` with the home cell and the visited cells."""
    held = classes.sparkSession.sparkContext.broadcast(books)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                x = levelled(stacked(part.column(2), d))
                unit = x / np.linalg.norm(x, axis=1, keepdims=True)
                cells = traversal(unit, held.value, visits).astype(np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, cells.size + 1, cells.shape[1], dtype=np.int32)), pa.array(cells.ravel()))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(np.ascontiguousarray(cells[:, 0])), lists], ["cid", "n", "v", "home", "cells"])

    return classes.select("cid", "n", "v").mapInArrow(run, "cid long, n long, v binary, home long, cells array<long>")


def _links(d: int, cosine: float):
    """Compare the homes and visitors of each cell: link counts per class (kind 0) and a spanning forest of links (kind 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        degree: dict[int, int] = {}
        left, right = [], []

        def add(ids: np.ndarray, n: np.ndarray) -> None:
            live = n > 0
            for i, m in zip(ids[live].tolist(), n[live].tolist(), strict=True):
                degree[i] = degree.get(i, 0) + m

        def compare(homes: dict, visitors: pa.RecordBatch) -> None:
            x = levelled(stacked(visitors.column("v"), d))
            ids, n, home = (visitors.column(c).to_numpy() for c in ("cid", "n", "home"))
            norm = np.linalg.norm(x, axis=1)
            for at in range(0, len(ids), 512):
                s = slice(at, at + 512)
                near = x[s] @ homes["x"].T / (norm[s][:, None] * homes["norm"][None, :]) >= cosine
                near &= ids[s][:, None] != homes["ids"][None, :]
                v, h = np.nonzero(near)
                # both may visit the other's home; such a pair counts where the visitor has the smaller id
                mutual = (homes["cells"][h] == home[s][v][:, None]).any(1)
                keep = ~mutual | (ids[s][v] < homes["ids"][h])
                v, h = v[keep], h[keep]
                add(ids[s], np.bincount(v, homes["n"][h], len(ids[s])).astype(np.int64))
                add(homes["ids"], np.bincount(h, n[s][v], len(homes["ids"])).astype(np.int64))
                a, b = forest(ids[s][v], homes["ids"][h])
                left.append(a)
                right.append(b)

        place, homes = None, None
        for batch in batches:
            key = batch.column("place").to_numpy()
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(key)) + 1, [len(key)]]) if len(key) else [0]
            for low, high in zip(cuts[:-1], cuts[1:], strict=True):
                part = batch.slice(low, high - low)
                if part.column("visitor")[0].as_py() == 0 or part.column("visitor")[len(part) - 1].as_py() == 0 or place != key[low]:
                    own = np.asarray(part.column("visitor")) == 0
                    mine = part.filter(pa.array(own))
                    x = levelled(stacked(mine.column("v"), d))
                    fresh = {"x": x, "norm": np.linalg.norm(x, axis=1), "ids": mine.column("cid").to_numpy(), "n": mine.column("n").to_numpy(), "cells": np.array(mine.column("cells").to_pylist(), np.int64).reshape(len(mine), -1)}
                    same = place == key[low] and homes is not None and len(homes["ids"])
                    homes = {c: np.concatenate([homes[c], fresh[c]]) if same and len(fresh["ids"]) else (homes[c] if same else fresh[c]) for c in fresh}
                    place = key[low]
                    part = part.filter(pa.array(~own))
                if len(part) and len(homes["ids"]):
                    compare(homes, part)
            if len(left) > 64:
                a, b = forest(np.concatenate(left), np.concatenate(right))
                left[:], right[:] = [a], [b]
        a, b = forest(np.concatenate(left), np.concatenate(right)) if left else (np.zeros(0, np.int64),) * 2
        ids, counts = np.array(list(degree), np.int64), np.array(list(degree.values()), np.int64)
        kind = np.concatenate([np.zeros(len(ids), np.int32), np.ones(len(a), np.int32)])
        yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(np.concatenate([ids, a])), pa.array(np.concatenate([counts, b]))], ["kind", "a", "b"])

    return run


def _linked(classes: DataFrame, n: int, d: int, cfg: IndexConfig) -> DataFrame | None:
    """Links among ``n`` classes of vectors of ``d`` components, as ``_links`` gives them; staged."""
    spark = classes.sparkSession
    share = min(1.0, cfg.sample / n)
    rows = classes.where(F.pmod(F.xxhash64("cid", F.lit(cfg.seed)), F.lit(1 << 30)) < int(share * (1 << 30))).select("v").limit(2 * cfg.sample).collect()
    if not rows or n < 2:
        return None
    books, visits = fit(np.frombuffer(b"".join(r[0] for r in rows), "<f8").reshape(-1, d), n, cfg)
    found = staged(_located(classes, books, visits, d), "located")
    # a cell's homes and its visitors are both dealt out, and every share of the one meets every share of the other
    visited = found.select(F.explode("cells").alias("_cell")).groupBy("_cell").agg(F.ceil(F.count("*") / cfg.visitors).cast("int").alias("_subs"))
    sizes = found.groupBy(F.col("home").alias("_home")).agg(F.ceil(F.count("*") / cfg.chunk).cast("int").alias("_parts"))
    sizes = staged(sizes.join(visited, F.col("_home") == F.col("_cell")).select("_cell", "_parts", "_subs"), "cells")
    homes = found.join(sizes, found["home"] == sizes["_cell"]).select(
        F.col("home").alias("cell"), F.pmod(F.xxhash64("cid"), F.col("_parts")).cast("int").alias("part"), F.explode(F.sequence(F.lit(0), F.col("_subs") - 1)).alias("sub"), F.lit(0).alias("visitor"), "cid", "n", "v", "home", "cells"
    )
    guests = found.select(F.explode("cells").alias("cell"), "cid", "n", "v", "home").join(sizes, F.col("cell") == F.col("_cell"))
    sub = F.pmod(F.xxhash64("cid", F.lit("sub")), F.col("_subs")).cast("int").alias("sub")
    guests = guests.select("cell", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1)).alias("part"), sub, F.lit(1).alias("visitor"), "cid", "n", "v", "home", F.array().cast("array<long>").alias("cells"))
    dealt = homes.unionByName(guests).withColumn("place", F.xxhash64("cell", "part", "sub"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = dealt.repartition(parts, "place").sortWithinPartitions("place", "visitor").select("place", "visitor", "cid", "n", "v", "home", "cells")
    return staged(dealt.mapInArrow(_links(d, cfg.cosine), "kind int, a long, b long"), "vector-links")


def near_vectors(frame: DataFrame, cfg: IndexConfig = IndexConfig()) -> DataFrame:
    """``(vec_id, embedding)`` → ``(vec_id, n_links, component_id, kept)``, one row per row.

    Equal vectors are one class, found by grouping, and link with each other.  Cells with many homes or visitors are dealt
    out in chunks.  Vectors are compared with those of as many components, one index for each number that occurs.  Vectors
    that are null, empty, zero, or hold null or non-finite components link with nothing, as do vectors whose only ids are null.
    """
    spark = frame.sparkSession
    parts = [usable(frame.where(F.size("embedding") == d), d).where(F.col("v") != F.lit(bytes(8 * d))) for d in widths(frame)]
    good = staged(reduce(DataFrame.unionByName, parts) if parts else usable(frame, 0).where(F.lit(False)), "vectors")
    classes = staged(good.groupBy("v").agg(F.min("vec_id").cast("long").alias("cid"), F.count("*").alias("n")).where("cid is not null"), "vector-classes")
    width = F.floor(F.octet_length("v") / 8).cast("int")
    found = [_linked(classes.where(width == r["d"]), r["count"], r["d"], cfg) for r in classes.groupBy(width.alias("d")).count().collect()]
    linked = reduce(DataFrame.unionByName, [f for f in found if f is not None], spark.createDataFrame([], "kind int, a long, b long"))
    degrees = linked.where("kind = 0").groupBy(F.col("a").alias("cid")).agg(F.sum("b").alias("links"))
    labels = components(linked.where("kind = 1").select(F.col("a").alias("u"), F.col("b").alias("v"))).select(F.col("node").alias("cid"), "component")
    done = classes.join(degrees, "cid", "left").join(labels, "cid", "left").select("v", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "cid").alias("component_id"))
    known = good.join(done, "v").select("vec_id", "n_links", "component_id")
    # each row once: vectors that count from `known`, the others as they are
    counted = known.groupBy("vec_id", "n_links", "component_id").count()
    rows = frame.select("vec_id").groupBy("vec_id").agg(F.count("*").alias("_all"))
    used = known.groupBy("vec_id").agg(F.count("*").alias("_used")).select(F.col("vec_id").alias("_id"), "_used")
    rest = rows.join(used, F.col("vec_id").eqNullSafe(F.col("_id")), "left").select("vec_id", (F.col("_all") - F.coalesce("_used", F.lit(0))).alias("count")).where("count > 0")
    rest = rest.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"), "count")
    out = counted.unionByName(rest).withColumn("_i", F.explode(F.sequence(F.lit(1).cast("long"), F.col("count"))))
    return out.select("vec_id", F.col("n_links").cast("long").alias("n_links"), "component_id", F.col("vec_id").eqNullSafe(F.col("component_id")).alias("kept"))


def op4_multiindex(spark, sf_dir: str) -> DataFrame:
    """Every row of ``embeddings`` with its links (cosine 0.95 or more to another row), the smallest vec_id reachable, and whether it is
    that one; null, empty, zero or non-finite vectors link with nothing, repeated rows come out each."""
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
