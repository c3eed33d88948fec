"""Exact top-k inner products by block-at-a-time pruning.

Candidates lie in blocks: ranges of a document order that puts vectors with equal sign patterns together.  A block has its
forward index (the components of its vectors) and the maximum and minimum of each term.  A query's bound for a block is the
sum over terms of the larger of query * maximum and query * minimum.  A query takes its blocks by falling bounds and scores
them whole, until the bounds lie below its k-th score; equal bounds are scored, as ties go to the smaller id.

Blocks travel in super-blocks, which have bounds of their own.  A first k-th score for each query comes from a bounded sample
of the candidates, and a query goes only to the super-blocks whose bound reaches it: what is shuffled are live pairs.  Groups
of queries meet packs of bounds and then super-blocks, one of each in a task, so its memory doesn't depend on the input.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from detspark.llm.vectors import matrix, widths
from detspark.plans.scratch import staged


@dataclass(frozen=True)
class TopkConfig:
    k: int = 20
    scale: int = 64
    every: int = 20
    block: int = 512
    blocks_per_task: int = 16
    query_group: int = 4096
    sample: int = 4096
    order_terms: int = 16
    bounds_per_pack: int = 4096


_EXACT = float(1 << 53)
_LONG = (1 << 63) - 1
_RESULT = "query_id long, rank int, vec_id long, score long"


def _whole(x: np.ndarray) -> np.ndarray:
    return np.array([int(v) for v in x.ravel()], object).reshape(x.shape)


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Integer inner products: in doubles where every sum is exact, else in Python's integers."""
    if not a.size or not b.size or a.shape[1] * np.abs(a).max() * np.abs(b).max() < _EXACT:
        return a @ b.T
    return _whole(a) @ _whole(b).T


def _below(scores: np.ndarray) -> np.ndarray:
    """Doubles that are no larger than the scores."""
    if scores.dtype != object:
        return scores.astype(float)
    top = int(np.finfo(float).max)
    near = np.array([float(max(-top, min(top, int(v)))) for v in scores.ravel()]).reshape(scores.shape)
    return np.nextafter(near, -np.inf)


def scaled(frame: DataFrame, d: int, cfg: TopkConfig) -> DataFrame:
    """``(vec_id, embedding)`` → ``vec_id, code, v``: floor(scale * x) as little-endian doubles (whole numbers), and the order code.

    Products beyond the range of doubles count as the largest double.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, values = matrix(batch.column(1), d)
            with np.errstate(over="ignore"):
                x = np.nan_to_num(np.floor(values * cfg.scale))
            code = ((x[:, : cfg.order_terms] >= 0).astype(np.int64) << np.arange(min(d, cfg.order_terms))).sum(1)
            raw = x.astype("<f8").tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows)).cast(pa.int64()), pa.array(code), pa.array([raw[i : i + 8 * d] for i in range(0, len(raw), 8 * d)], pa.binary())], ["vec_id", "code", "v"])

    return frame.select("vec_id", "embedding").mapInArrow(run, "vec_id long, code long, v binary")


def _gathered(size: int):
    """Rows ``(row, vec_id, v)`` of a task, in order, as records of at most ``size`` vectors."""

    def pack(rows: list, ids: list, cells: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([x], pa.binary()) for x in (np.array(rows, np.int64).tobytes(), np.array(ids, np.int64).tobytes(), b"".join(cells))], ["rows", "ids", "x"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[list, list, list] = [], [], []
        for batch in batches:
            for kept, column in zip(held, batch.columns, strict=True):
                kept += column.to_pylist()
            while len(held[0]) >= size:
                yield pack(*(x[:size] for x in held))
                held = tuple(x[size:] for x in held)
        if held[0]:
            yield pack(*held)

    return run


def best(query: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of each query: highest score, then smallest id."""
    if score.dtype == object:
        order = np.array(sorted(range(len(query)), key=lambda i: (query[i], -score[i], ids[i])), np.int64)
    else:
        order = np.lexsort((ids, -score, query))
    q = query[order]
    starts = np.flatnonzero(np.concatenate([[True], q[1:] != q[:-1]])) if len(q) else np.zeros(0, np.int64)
    rank = np.arange(len(q)) - np.repeat(starts, np.diff(np.append(starts, len(q))))
    return order[rank < k]


def ceilings(queries: np.ndarray, top: np.ndarray, low: np.ndarray) -> np.ndarray:
    """Bounds of each query's scores in each range of vectors with term maxima ``top`` and minima ``low``.

    Sums in doubles may be off by a little for very large components, so a little is added; bounds that can't be told are infinite.
    """
    up, down = np.maximum(queries, 0), np.minimum(queries, 0)
    with np.errstate(over="ignore", invalid="ignore"):
        slack = 1e-9 * (up @ np.abs(top).T - down @ np.abs(low).T)
        bound = up @ top.T + down @ low.T + np.where(slack < 1e3, 0.0, slack)
    return np.where(np.isnan(bound), np.inf, bound)


def search(query_rows: np.ndarray, queries: np.ndarray, floor: np.ndarray, blocks: list[tuple[np.ndarray, np.ndarray, np.ndarray]], k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query place, id, score) of each query's k best in ``blocks`` (rows, ids, vectors) that reach ``floor``, own row left out."""
    top, low = np.array([x.max(0) for _, _, x in blocks]), np.array([x.min(0) for _, _, x in blocks])
    kth = floor.astype(float).copy()
    bound = ceilings(queries, top, low)
    order = np.argsort(-bound, 1, kind="stable")
    held_q, held_id, held_s = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    everyone = np.arange(len(queries))
    for step in range(len(blocks)):
        at = order[:, step]
        live = bound[everyone, at] >= kth
        if not live.any():
            break
        found = [(held_q, held_id, held_s)]
        for b in np.unique(at[live]).tolist():
            who = np.flatnonzero(live & (at == b))
            rows, ids, x = blocks[b]
            scores = _product(queries[who], x)
            good = (scores >= kth[who][:, None]).astype(bool) & (query_rows[who][:, None] != rows[None, :])
            q, c = np.nonzero(good)
            found.append((who[q], ids[c], scores[q, c]))
        held_q, held_id, held_s = (np.concatenate([f[i] for f in found]) for i in range(3))
        keep = best(held_q, held_id, held_s, k)
        held_q, held_id, held_s = held_q[keep], held_id[keep], held_s[keep]
        counts = np.bincount(held_q, minlength=len(queries))
        last = np.cumsum(counts) - 1
        full = counts >= k
        kth[full] = np.maximum(kth[full], _below(held_s[last[full]]))
    return held_q, held_id, held_s


def _floors(rows: DataFrame, asked: DataFrame, n: int, d: int, cfg: TopkConfig) -> DataFrame:
    """``asked`` with ``floor``: the k-th best score against a sample of at most 2 * ``sample`` rows, which the k-th best of all reaches."""
    share = min(1.0, cfg.sample / max(1, n))
    drawn = rows.where(F.pmod(F.xxhash64("row", F.lit("seed")), F.lit(1 << 30)) < int(share * (1 << 30))).select("row", "v").limit(2 * cfg.sample).collect()
    held = rows.sparkSession.sparkContext.broadcast((np.array([r[0] for r in drawn], np.int64), np.frombuffer(b"".join(r[1] for r in drawn), "<f8").reshape(-1, d)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, x_s = held.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                row = part.column(0).to_numpy()
                x = np.frombuffer(b"".join(part.column(2).to_pylist()), "<f8").reshape(-1, d)
                floor = np.full(len(row), -np.inf)
                if len(of) > cfg.k:
                    s = _below(_product(x, x_s))
                    s[row[:, None] == of[None, :]] = -np.inf
                    floor = np.partition(s, s.shape[1] - cfg.k, axis=1)[:, s.shape[1] - cfg.k]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(floor)], ["row", "query_id", "v", "g", "floor"])

    return asked.select("row", F.col("vec_id").alias("query_id"), "v", "g").mapInArrow(run, "row long, query_id long, v binary, g long, floor double")


def live_pairs(asked: DataFrame, blocks: DataFrame, groups: int, d: int, cfg: TopkConfig) -> DataFrame:
    """``(super, g, row)``: the super-blocks that each query has to visit, by the bounds of whole super-blocks alone.

    Bounds are two vectors a super-block, so here a query meets a row for thousands of candidates.
    """

    def extremes(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        x = [np.frombuffer(v, "<f8").reshape(-1, d) for v in frame["x"]]
        top, low = np.max([v.max(0) for v in x], 0), np.min([v.min(0) for v in x], 0)
        return pd.DataFrame({"super": [key[0]], "pack": [key[0] // cfg.bounds_per_pack], "top": [top.tobytes()], "low": [low.tobytes()]})

    bounds = staged(blocks.select("super", "x").groupBy("super").applyInPandas(extremes, "super long, pack long, top binary, low binary"), "bounds")
    packs = bounds.select("pack").distinct()
    meet = staged(packs.withColumn("g", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long")))), "pairs")

    def run(key: tuple, queries: pd.DataFrame, ranges: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(ranges):
            return pd.DataFrame({"super": np.zeros(0, np.int64), "g": np.zeros(0, np.int64), "row": np.zeros(0, np.int64)})
        x = np.frombuffer(b"".join(queries["v"]), "<f8").reshape(-1, d)
        top, low = (np.frombuffer(b"".join(ranges[c]), "<f8").reshape(-1, d) for c in ("top", "low"))
        out = []
        for at in range(0, len(x), 512):
            q, s = np.nonzero(ceilings(x[at : at + 512], top, low) >= queries["floor"].to_numpy()[at : at + 512, None])
            out.append(pd.DataFrame({"super": ranges["super"].to_numpy()[s], "g": key[1], "row": queries["row"].to_numpy()[at + q]}))
        return pd.concat(out)

    left = asked.join(meet, "g").groupBy("pack", "g")
    ranges = bounds.join(meet.select("pack", F.col("g").alias("of")), "pack").select(F.col("pack").alias("in"), "of", "super", "top", "low")
    return left.cogroup(ranges.groupBy("in", "of")).applyInPandas(run, "super long, g long, row long")


def _of_width(frame: DataFrame, d: int, cfg: TopkConfig) -> DataFrame:
    """The search among the vectors of ``d`` components.  Rows are named by a number that is staged with them."""
    rows = staged(scaled(frame, d, cfg).where("vec_id is not null").withColumn("row", F.monotonically_increasing_id()), "scaled")
    n = rows.count()
    ranges = max(1, -(-n // (cfg.block * cfg.blocks_per_task)))
    ordered = rows.repartitionByRange(ranges, "code", "row").sortWithinPartitions("code", "row").select("row", "vec_id", "v")
    blocks = staged(ordered.mapInArrow(_gathered(cfg.block), "rows binary, ids binary, x binary").withColumn("super", F.spark_partition_id().cast("long")), "blocks")
    asked = rows.where(F.col("vec_id") % cfg.every == 0)
    groups = max(1, -(-asked.count() // cfg.query_group))
    asked = asked.withColumn("g", F.pmod(F.xxhash64("row"), F.lit(groups)).cast("long"))
    asked = staged(_floors(rows, asked, n, d, cfg), "queries")
    live = staged(live_pairs(asked, blocks, groups, d, cfg), "live")
    left = asked.drop("g").join(live, "row").select("super", "g", "row", "query_id", "v", "floor")
    wanted = live.select(F.col("super").alias("in"), F.col("g").alias("of")).distinct()
    right = blocks.join(wanted, F.col("super") == F.col("in")).select("in", "of", "rows", "ids", "x")

    def run(key: tuple, queries: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(held):
            return pd.DataFrame({"row": np.zeros(0, np.int64), "query_id": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "high": np.zeros(0, np.int64), "score": np.zeros(0, np.int64)})
        of = queries["row"].to_numpy()
        x = np.frombuffer(b"".join(queries["v"]), "<f8").reshape(-1, d)
        forward = [(np.frombuffer(r, np.int64), np.frombuffer(i, np.int64), np.frombuffer(v, "<f8").reshape(-1, d)) for r, i, v in zip(held["rows"], held["ids"], held["x"], strict=True)]
        q, c, s = search(of, x, queries["floor"].to_numpy(), forward, cfg.k)
        if s.dtype == object:  # scores beyond 64 bits: ordered as far as they exceed them, and cut to them
            score = np.array([max(-_LONG, min(_LONG, int(v))) for v in s], np.int64)
            high = np.array([str(int(v) - int(w)) for v, w in zip(s, score, strict=True)], object)
        else:
            score, high = s.astype(np.int64), np.full(len(s), "0", object)
        return pd.DataFrame({"row": of[q], "query_id": queries["query_id"].to_numpy()[q], "vec_id": c, "high": high, "score": score})

    found = left.groupBy("super", "g").cogroup(right.groupBy("in", "of")).applyInPandas(run, "row long, query_id long, vec_id long, high string, score long")
    negative = F.col("high").startswith("-")
    size = F.length("high")
    # the excess as a number in text: sign, length, digits
    excess = [negative.cast("int"), F.when(negative, size).otherwise(-size), F.when(negative, F.col("high")), F.desc(F.when(~negative, F.col("high")))]
    order = Window.partitionBy("row").orderBy(*excess, F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= cfg.k).select("query_id", "rank", "vec_id", "score")


def exact_topk(frame: DataFrame, cfg: TopkConfig = TopkConfig()) -> DataFrame:
    """``(vec_id, embedding)`` → ``(query_id, rank, vec_id, score)``.

    Vectors that are null, without components, hold null or non-finite components or have no id take no part.  Vectors are
    compared with those of as many components, one pass for each number that occurs.  Every row whose id is divisible by
    ``every`` is a query of its own, also where ids repeat, and meets all rows but itself.  Scores are compared exactly; one
    beyond 64 bits is reported as the largest or smallest whole number of the type.  An empty table gives no rows.
    """
    parts = [_of_width(frame.where(F.size("embedding") == d), d, cfg) for d in widths(frame)]
    return reduce(DataFrame.unionByName, parts) if parts else frame.sparkSession.createDataFrame([], _RESULT)


def op6_topk(spark, sf_dir: str) -> DataFrame:
    """For each row of ``embeddings`` whose vec_id is divisible by 20 its 20 highest integer inner products with other rows, ties to
    the smaller vec_id; null, empty or non-finite vectors and rows without id take no part, repeated ids are asked each."""
    return exact_topk(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
